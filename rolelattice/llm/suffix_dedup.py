"""Removal of repeated strings by suffix arrays: every byte that a string of LENGTH bytes covers which starts elsewhere, too.

1. Anchors. Each window of LENGTH bytes names the place of the least hash among its first WIDTH eight-byte words. Equal
   windows name the same place in themselves, so a text falls into stretches of window starts with a common anchor, and equal
   windows lie in stretches whose anchors are followed by the same bytes. Stretches are grouped by the hash of those bytes.
2. A group of one stretch repeats nothing. Equal stretches count as one with its number of copies; if a group has one
   distinct stretch, all its windows repeat or none does.
3. Groups of several distinct stretches form shards of bounded size. Each shard gets a suffix array by rank refinement and
   common prefixes; neighbours that share LENGTH bytes repeat. Stretches of a shard that is searched in parts are matched
   across the parts by binary search.
4. Groups beyond a bound (a common line in many different surroundings) are split by longer contexts first, and
   what is left is counted by whole windows, so that no task holds an unbounded group.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import chunks, cut, mix, parts, prefix_hash, span_hash, stored, table
from .suffixes import bounds, kasai, refine, words8

LENGTH, WIDTH = 400, 280
#: Bytes after an anchor that each of its windows holds.
CONTEXT = LENGTH - WIDTH + 1
#: Distinct stretches of a group that a shard takes, and bytes at which a shard is closed.
GROUP_MOST, SHARD_BYTES = 3000, 2 << 20
#: Window starts that a split stretch keeps.
SPLIT = 48
_PLACE_BITS = 31


def anchors(raw: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First and last window start and anchor of each stretch (places in raw)."""
    n = len(raw)
    lens = np.diff(offs)
    if not (lens >= LENGTH).any():
        z = np.zeros(0, np.int64)
        return z, z, z
    v = mix(words8(raw) + np.uint64(1))
    v = (v >> np.uint64(_PLACE_BITS) << np.uint64(_PLACE_BITS)) | np.arange(n, dtype=np.uint64)
    pad = -n % WIDTH
    grid = np.concatenate([v, np.full(pad + WIDTH, np.iinfo(np.uint64).max)]).reshape(-1, WIDTH)
    left = np.minimum.accumulate(grid, axis=1).ravel()
    right = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    least = np.minimum(right[:n], left[WIDTH - 1 : n + WIDTH - 1])
    ok = np.zeros(n + 1, np.int64)
    long = lens >= LENGTH
    np.add.at(ok, offs[:-1][long], 1)
    np.add.at(ok, offs[1:][long] - LENGTH + 1, -1)
    start = np.flatnonzero(np.cumsum(ok[:-1]) > 0)
    place = (least[start] & np.uint64((1 << _PLACE_BITS) - 1)).astype(np.int64)
    first = np.append(True, (place[1:] != place[:-1]) | (np.diff(start) > 1))
    last = np.append(first[1:], True)
    return start[first], start[last], place[first]


def _signed(h: np.ndarray) -> pa.Array:
    return pa.array(h.view(np.int64))


def stretches(docs: DataFrame) -> DataFrame:
    """_id, _key, a, b, at, h, s: window starts a to b (bytes) of a text with a common anchor at a + at, hashes of the anchor's context and of all bytes of the stretch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, raw, offs in chunks(batches, "_body"):
            a, b, p = anchors(raw, offs)
            if not len(a):
                continue
            doc = np.searchsorted(offs, a, "right") - 1
            pre = prefix_hash(raw)
            h, s = span_hash(pre, p, p + CONTEXT), span_hash(pre, a, b + LENGTH)
            take = pa.array(doc)
            yield pa.RecordBatch.from_arrays([rows.column(0).take(take), rows.column(1).take(take), pa.array((a - offs[doc]).astype(np.int32)), pa.array((b - offs[doc]).astype(np.int32)), pa.array((p - a).astype(np.int32)), _signed(h), _signed(s ^ mix((b - a).astype(np.uint64)))], ["_id", "_key", "a", "b", "at", "h", "s"])

    return docs.select("_id", "_key", "_body").mapInArrow(run, "_id bigint, _key bigint, a int, b int, at int, h bigint, s bigint")


def to_ranges(flags: np.ndarray) -> list[tuple[int, int]]:
    edge = np.flatnonzero(np.diff(np.concatenate([[0], flags.astype(np.int8), [0]])))
    return list(zip(edge[::2].tolist(), (edge[1::2] - 1).tolist(), strict=True))


def repeated(texts: list[bytes], part_bytes: int | None = None) -> list[np.ndarray]:
    """Per text a flag for each window start: its LENGTH bytes also start at another place of these texts.

    With part_bytes, the texts are split in parts with a suffix array each, and windows that are unique in their part are
    looked for in the others by binary search."""
    lens = np.array([len(t) for t in texts])
    if part_bytes and lens.sum() > part_bytes:
        cuts = np.unique(np.searchsorted(np.cumsum(lens), np.arange(part_bytes, lens.sum() + part_bytes, part_bytes), "left"))
        groups = [g for g in np.split(np.arange(len(texts)), np.clip(cuts + 1, 0, len(texts))) if len(g)]
    else:
        groups = [np.arange(len(texts))]
    out: list[np.ndarray] = [np.zeros(0, bool)] * len(texts)
    made = []
    for g in groups:
        buf = np.frombuffer(b"".join(texts[i] for i in g), np.uint8)
        ends = np.repeat(np.cumsum(lens[g]), lens[g])
        # what lies beyond a text's end must not order it: its last words are cut there
        w = words8(buf)
        short = np.flatnonzero(ends - np.arange(len(buf)) < 8)
        w[short] &= ~((np.uint64(1) << ((8 - (ends[short] - short)) * 8).astype(np.uint64)) - np.uint64(1))
        order = refine(w, 8, 2 * LENGTH, ends)
        lcp = kasai(buf, order, ends, LENGTH)
        long = lcp >= LENGTH
        flag = np.zeros(len(buf), bool)
        flag[order[long]] = True
        flag[order[np.append(long[1:], False)]] = True
        made.append((g, buf, ends, order, flag))
    for k, (g, buf, ends, _, flag) in enumerate(made if len(made) > 1 else []):
        at = np.flatnonzero(~flag & (ends - np.arange(len(buf)) >= LENGTH))
        for j, (_, other, other_ends, order, _) in enumerate(made):
            if j != k and len(at):
                whole = order[other_ends[order] - order >= LENGTH]  # only these can hold a window; their order stays
                for c in range(0, len(at), 4096):
                    q = at[c : c + 4096]
                    low, high = bounds(other, whole, buf[q[:, None] + np.arange(LENGTH)].astype(np.int64), np.full(len(q), LENGTH))
                    flag[q[high > low]] = True
    for g, _, _, _, flag in made:
        at = 0
        for i in g:
            out[i] = flag[at : at + max(0, lens[i] - LENGTH + 1)]
            at += lens[i]
    return out


_FOUND = "h bigint, s bigint, ranges array<struct<lo:int,hi:int>>"
_RANGES = pa.list_(pa.struct([("lo", pa.int32()), ("hi", pa.int32())]))


def _found(h: list, s: list, ranges: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(s, pa.int64()), pa.array([[{"lo": a, "hi": b} for a, b in r] for r in ranges], _RANGES)], ["h", "s", "ranges"])


def shared_length(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    low, high = 0, min(len(a), len(b))
    if a[:high] == b[:high]:
        return high
    while low < high - 1:  # a and b agree up to low and differ before high
        mid = (low + high) // 2
        if a[low:mid] == b[low:mid]:
            low = mid
        else:
            high = mid
    return low


def longest_shared(sides: list[bytes]) -> list[int]:
    """For each the longest prefix that it shares with another one: that with a neighbour in sorted order."""
    order = sorted(range(len(sides)), key=sides.__getitem__)
    out = [0] * len(sides)
    for i, j in zip(order, order[1:], strict=False):
        n = shared_length(sides[i], sides[j])
        out[i], out[j] = max(out[i], n), max(out[j], n)
    return out


def may_repeat(group: list[tuple[int, int, bytes]]) -> list[tuple[int, bytes]]:
    """Of distinct stretches (s, at, body) with one anchor context those that may share a window with another one.

    Equal windows have their anchors at the same place, so the bytes they share lie around the anchor: at most the longest run
    shared to its left and the longest to its right."""
    left = longest_shared([body[:at][::-1] for _, at, body in group])
    right = longest_shared([body[at:] for _, at, body in group])
    return [(s, body) for (s, _, body), x, y in zip(group, left, right, strict=True) if x + y >= LENGTH]


def by_arrays(groups: DataFrame) -> DataFrame:
    """h, s, at, body -> h, s, ranges of repeated window starts; a group is whole in one shard, a shard holds groups up to SHARD_BYTES."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], bytes] = {}
        size, now = 0, None

        def close() -> pa.RecordBatch:
            flags = repeated(list(held.values()), 4 * SHARD_BYTES)
            got = [(k, r) for k, f in zip(held, flags, strict=True) if (r := to_ranges(f))]
            return _found([k[0] for k, _ in got], [k[1] for k, _ in got], [r for _, r in got])

        group: dict[int, tuple[int, int, bytes]] = {}

        def gather() -> None:
            nonlocal size
            kept = may_repeat(list(group.values())) if len(group) > 1 else []
            for s, body in kept if len(kept) > 1 else ():
                held[now, s] = body
                size += len(body)
            group.clear()

        for b in batches:
            for h, s, at, body in zip(*[b.column(i).to_pylist() for i in range(4)], strict=True):
                if h != now:
                    gather()
                    now = h
                    if size >= SHARD_BYTES:
                        yield close()
                        held.clear()
                        size = 0
                group.setdefault(s, (s, at, body))
        gather()
        if held:
            yield close()

    return groups.select("h", "s", "at", "body").repartition(parts(groups.sparkSession), "h").sortWithinPartitions("h", "s").mapInArrow(run, _FOUND)


def by_windows(large: DataFrame) -> DataFrame:
    """h, s, at (anchor in body), body of large groups -> h, s, ranges. Stretches are split to SPLIT starts and go on only where another has the same longer context; then whole windows are counted."""

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[list] = [[], [], [], [], []]
            for h, s, at, body in zip(*[b.column(i).to_pylist() for i in range(4)], strict=True):
                starts = len(body) - LENGTH + 1
                # places are counted from the anchor, so that equal windows fall into the same part
                for part in range((-at) // SPLIT, (starts - 1 - at) // SPLIT + 1):
                    lo, hi = max(0, part * SPLIT + at), min(starts, (part + 1) * SPLIT + at)
                    core = body[max(0, (part + 1) * SPLIT + at - 1) : part * SPLIT + at + LENGTH]  # what each of these windows holds
                    key = hashlib.blake2b(core, digest_size=8, salt=str(part).encode()[:16]).digest()
                    for col, v in zip(out, (h, s, int.from_bytes(key, "little", signed=True), lo, body[lo : hi - 1 + LENGTH]), strict=True):
                        col.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.int64()), pa.array(out[3], pa.int32()), pa.array(out[4], pa.binary())], ["h", "s", "core", "lo", "body"])

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, raw, offs in chunks(batches, "body"):
            pre = prefix_hash(raw)
            n = np.maximum(np.diff(offs) - LENGTH + 1, 0)
            row = np.repeat(np.arange(len(n)), n)
            at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            x = offs[row] + at
            one = span_hash(pre, x, x + LENGTH)
            two = mix(span_hash(pre, x, x + LENGTH // 2) * np.uint64(3) + span_hash(pre, x + LENGTH // 3, x + LENGTH))
            take = pa.array(row)
            lo = np.asarray(rows.column(3))[row] + at
            yield pa.RecordBatch.from_arrays([rows.column(0).take(take), rows.column(1).take(take), pa.array(lo.astype(np.int32)), _signed(one), _signed(two)], ["h", "s", "x", "w1", "w2"])

    pieces = cut(large.select("h", "s", "at", "body").mapInArrow(split, "h bigint, s bigint, core bigint, lo int, body binary"))
    shared = pieces.groupBy("core").count().where("count > 1").select("core")
    each = cut(pieces.join(shared, "core").select("h", "s", "core", "lo", "body").mapInArrow(windows, "h bigint, s bigint, x int, w1 bigint, w2 bigint"))
    twice = each.groupBy("w1", "w2").count().where("count > 1").select("w1", "w2")
    return each.join(twice, ["w1", "w2"]).groupBy("h", "s").agg(F.transform(F.sort_array(F.collect_set("x")), lambda x: F.struct(x.alias("lo"), x.alias("hi"))).alias("ranges"))


def keyed(docs: DataFrame) -> DataFrame:
    """_id, _key, _body: a document is named by its id (null: the least number) and its text's hash."""
    body = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)).cast("long")).alias("_id"), F.xxhash64(body).alias("_key"), body.alias("_body"))


def repeats(docs: DataFrame) -> DataFrame:
    """_id, _key, starts: ranges (lo, hi) of the window starts of a document whose LENGTH bytes start elsewhere, too."""
    texts = keyed(docs)
    found = stretches(texts)
    kinds = stored(found.groupBy("h", "s").agg(F.count("*").alias("copies")))
    groups = kinds.groupBy("h").agg(F.count("*").alias("kinds"), F.sum("copies").alias("rows")).where("rows > 1").select("h", "kinds")
    shared = kinds.join(groups, "h").where("kinds > 1 or copies > 1")
    at = cut(found.join(shared, ["h", "s"]).select("_id", "_key", "a", "b", "at", "h", "s", "kinds", "copies"))
    alone = at.where("copies > 1").select("_id", "_key", "a", F.array(F.struct(F.lit(0).alias("lo"), (F.col("b") - F.col("a")).alias("hi"))).alias("ranges"))
    # one place of each distinct stretch in a group with several
    chosen = at.where("kinds > 1").groupBy("h", "s").agg(F.min(F.struct("_id", "_key", "a", "b", "at")).alias("r"), F.first("kinds").alias("kinds"))
    per_doc = chosen.groupBy(F.col("r._id").alias("_id"), F.col("r._key").alias("_key")).agg(F.collect_list(F.struct("h", "s", F.col("r.a").alias("a"), F.col("r.b").alias("b"), F.col("r.at").alias("at"), "kinds")).alias("_want"))

    def bodies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[list] = [[], [], [], [], []]
            size = 0
            for body, want in zip(b.column(0), b.column(1).to_pylist(), strict=True):
                text = body.as_buffer().to_pybytes()
                for w in want:
                    for col, v in zip(out, (w["h"], w["s"], w["kinds"], w["at"], text[w["a"] : w["b"] + LENGTH]), strict=True):
                        col.append(v)
                    size += w["b"] - w["a"] + LENGTH
                if size > 1 << 22:
                    yield _bodies(out)
                    out, size = [[], [], [], [], []], 0
            yield _bodies(out)

    def _bodies(out: list[list]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.int64()), pa.array(out[3], pa.int32()), pa.array(out[4], pa.binary())], ["h", "s", "kinds", "at", "body"])

    held = cut(texts.join(per_doc, ["_id", "_key"]).select("_body", "_want").mapInArrow(bodies, "h bigint, s bigint, kinds bigint, at int, body binary"))
    judged = by_arrays(held.where(F.col("kinds") <= GROUP_MOST))
    large = held.where(F.col("kinds") > GROUP_MOST)
    if large.take(1):
        judged = judged.union(by_windows(large))
    some = at.where("kinds > 1 and copies = 1").join(judged, ["h", "s"]).select("_id", "_key", "a", "ranges")
    lo_hi = alone.union(some).select("_id", "_key", F.explode(F.transform("ranges", lambda r: F.struct((r["lo"] + F.col("a")).alias("lo"), (r["hi"] + F.col("a")).alias("hi")))).alias("r"))
    return lo_hi.distinct().groupBy("_id", "_key").agg(F.sort_array(F.collect_list("r")).alias("starts"))


def remove(docs: DataFrame) -> DataFrame:
    """doc_id, kept (bytes left), n_bytes, n_removed, n_spans."""
    body = keyed(docs).withColumns({"doc_id": F.when(F.col("_id") != F.lit(-(1 << 63)).cast("long"), F.col("_id"))})
    joined = body.join(repeats(docs), ["_id", "_key"], "left").select("doc_id", "_body", "starts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[list] = [[], [], [], []]
            for body, starts in zip(b.column(1), b.column(2).to_pylist(), strict=True):
                text = body.as_buffer().to_pybytes()
                kept, done, spans = [], 0, 0
                end = -1
                for r in starts or ():
                    if r["lo"] > end:
                        kept.append(text[done : r["lo"]] if end < 0 else text[end : r["lo"]])
                        spans += 1
                    end = max(end, r["hi"] + LENGTH)
                kept.append(text[end:] if end >= 0 else text)
                left = b"".join(kept)
                for col, v in zip(out, (left, len(text), len(text) - len(left), spans), strict=True):
                    col.append(v)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out[0], pa.binary()), *[pa.array(c, pa.int64()) for c in out[1:]]], ["doc_id", "kept", "n_bytes", "n_removed", "n_spans"])

    return joined.mapInArrow(run, "doc_id bigint, kept binary, n_bytes bigint, n_removed bigint, n_spans bigint")


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Null and empty texts have no bytes; repeated rows repeat each other; an empty table gives no rows."""
    out = remove(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"), F.octet_length("kept").cast("long").alias("n_kept"))
