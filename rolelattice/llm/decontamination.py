"""Benchmark decontamination by suffix arrays over the training text.

Each batch of documents is a shard with its own suffix array over word numbers. Words that no benchmark item has end
every match, so only runs of known words that are as long as the shortest window enter the array. Every benchmark suffix
is looked up in each shard by binary search with its first WINDOW words; the ranges give all occurrences and their places, and
occurrences of successive suffixes at successive places are one longer match.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import chunks, lower_table, table, utf8, word_hashes
from .suffixes import bounds, refine

WINDOW = 13
#: Benchmark words that are matched in one block, about 60 bytes a word; a larger benchmark takes further blocks, up to MOST_BLOCKS.
BLOCK_WORDS, MOST_BLOCKS = 1_000_000, 16


def kinds() -> np.ndarray:
    """1 for the bytes of words: digits, letters (of either case before lowering) and bytes beyond ASCII."""
    t = np.zeros(256, np.uint8)
    for a, b in ((48, 58), (65, 91), (97, 123), (128, 256)):
        t[a:b] = 1
    return t


def index_items(ids: list[str], texts: pa.Array) -> dict:
    """A block of the benchmark as arrays: its words' hashes; its windows as rows of word numbers; where each window is (item, word)."""
    raw, offs = utf8(texts)
    h, first, _, _ = word_hashes(raw, offs, kinds(), lower_table())
    vocab, number = np.unique(h, return_inverse=True)
    size = np.diff(first)
    wide = np.minimum(size, WINDOW)
    count = np.where(size > 0, size - wide + 1, 0)
    item = np.repeat(np.arange(len(ids)), count)
    word = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    lens = wide[item]
    inside = np.arange(WINDOW) < lens[:, None]
    at = (first[:-1][item] + word)[:, None] + np.arange(WINDOW)
    windows = np.where(inside, number[np.minimum(at, len(number) - 1)] if len(number) else 0, -1).astype(np.int32).reshape(-1, WINDOW)
    keys, which = np.unique(np.column_stack([lens, windows]).astype(np.int32), axis=0, return_inverse=True) if len(lens) else (np.zeros((0, WINDOW + 1), np.int32), np.zeros(0, np.int64))
    order = np.argsort(which.reshape(-1), kind="stable")
    return {"vocab": vocab, "windows": keys[:, 1:], "lens": keys[:, 0].astype(np.int64), "item_ids": ids, "items": item[order], "words": word[order], "at": np.searchsorted(which.reshape(-1)[order], np.arange(len(keys) + 1))}


def spread(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """first[i], first[i] + 1, ..., count[i] of them, for all i one after the other."""
    return np.arange(count.sum()) + np.repeat(first - (np.cumsum(count) - count), count)


def match(raw: np.ndarray, offs: np.ndarray, blocks: list[dict], places: bool = False) -> tuple[np.ndarray, np.ndarray, list[set], list[list]]:
    """Per row: words, hit words, items that occur, and (with places) matches (item, its word, the row's word, words), as long as they go."""
    h, first, _, _ = word_hashes(raw, offs, kinds(), lower_table())
    rows = len(offs) - 1
    cover = np.zeros(len(h) + 1, np.int64)
    found: list[set] = [set() for _ in range(rows)]
    matches: list[list] = [[] for _ in range(rows)]
    for b in blocks:
        if not len(b["lens"]):
            continue
        at = np.minimum(np.searchsorted(b["vocab"], h), len(b["vocab"]) - 1)
        known = b["vocab"][at] == h
        # runs of known words within a document; shorter ones than any window cannot match
        change = np.zeros(len(h) + 1, bool)
        change[[0, len(h)]] = True
        change[first] = True
        change[1 : len(h)] |= known[1:] != known[:-1]
        edge = np.flatnonzero(change)
        starts, ends = edge[:-1], edge[1:]
        ok = known[starts] & (ends - starts >= b["lens"].min()) if len(starts) else np.zeros(0, bool)
        starts, ends = starts[ok], ends[ok]
        if not len(starts):
            continue
        size = ends - starts + 1  # a separator after each run
        base = np.concatenate([[0], np.cumsum(size)])
        word = np.arange(base[-1]) - np.repeat(base[:-1] - starts, size)
        last = np.zeros(base[-1], bool)
        last[base[1:] - 1] = True
        seq = np.where(last, -1, at[np.minimum(word, len(h) - 1)])
        order = refine(seq, 1, WINDOW)
        low, high = bounds(seq, order, b["windows"], b["lens"])
        p = word[order[spread(low, high - low)]]
        w = np.repeat(np.arange(len(low)), high - low)
        np.add.at(cover, p, 1)
        np.add.at(cover, p + b["lens"][w], -1)
        doc = np.searchsorted(first, p, "right") - 1
        pair = np.unique(doc * len(low) + w)
        per = b["at"][pair % len(low) + 1] - b["at"][pair % len(low)]
        item = b["items"][spread(b["at"][pair % len(low)], per)]
        for x in np.unique(np.repeat(pair // len(low), per) * len(b["item_ids"]) + item).tolist():
            found[x // len(b["item_ids"])].add(b["item_ids"][x % len(b["item_ids"])])
        if places and len(p):
            per = b["at"][w + 1] - b["at"][w]
            entry = spread(b["at"][w], per)
            p, doc, w = np.repeat(p, per), np.repeat(doc, per), np.repeat(w, per)
            item, own = b["items"][entry], b["words"][entry]
            turn = np.lexsort((p, p - own, item, doc))
            p, doc, w, item, own = p[turn], doc[turn], w[turn], item[turn], own[turn]
            new = np.append(True, (doc[1:] != doc[:-1]) | (item[1:] != item[:-1]) | (p[1:] - own[1:] != p[:-1] - own[:-1]) | (p[1:] != p[:-1] + 1))
            begin = np.flatnonzero(new)
            end = np.append(begin[1:], len(p)) - 1
            long = p[end] - p[begin] + b["lens"][w[end]]
            for d, i, o, at_, n in zip(doc[begin].tolist(), item[begin].tolist(), own[begin].tolist(), (p[begin] - first[doc[begin]]).tolist(), long.tolist(), strict=True):
                matches[d].append((b["item_ids"][i], o, at_, n))
    hit = np.concatenate([[0], np.cumsum(np.cumsum(cover[:-1]) > 0)])
    return np.diff(first), hit[first[1:]] - hit[first[:-1]], found, matches


def longest_match(raw: np.ndarray, offs: np.ndarray, query: str) -> tuple[int, list[tuple[int, int]]]:
    """Words of the longest prefix of query that occurs in the rows, and its places (row, word)."""
    kind, low = kinds(), lower_table()
    h, first, _, _ = word_hashes(raw, offs, kind, low)
    q = np.frombuffer(query.encode("utf-8", "replace"), np.uint8)
    qh, _, _, _ = word_hashes(q, np.array([0, len(q)]), kind, low)
    vocab = np.unique(np.concatenate([h, qh]))
    size = np.diff(first) + 1
    base = np.concatenate([[0], np.cumsum(size)])
    seq = np.full(base[-1], -1, np.int64)
    row = np.repeat(np.arange(len(size)), size - 1)
    seq[np.arange(len(h)) + row] = np.searchsorted(vocab, h)
    order = refine(seq, 1, len(qh))
    numbers = np.searchsorted(vocab, qh)[None, :]
    best, places = 0, np.zeros(0, np.int64)
    low_k, high_k = 1, len(qh)
    while low_k <= high_k:
        k = (low_k + high_k) // 2
        a, b = bounds(seq, order, numbers, np.array([k]))
        if b[0] > a[0]:
            best, places, low_k = k, order[a[0] : b[0]], k + 1
        else:
            high_k = k - 1
    rows = np.searchsorted(base, places, "right") - 1
    return best, sorted((int(r), int(p - base[r])) for r, p in zip(rows, places, strict=True))


OUT = (("n_words", "bigint"), ("n_hit", "bigint"), ("n_items", "bigint"), ("items_sha256", "string"), ("contaminated", "boolean"))
PLACES = ("matches", "array<struct<item_id:string,item_word:bigint,doc_word:bigint,words:bigint>>")


def blocks_of(benchmark: DataFrame, block_words: int | None = None) -> list:
    """The benchmark in broadcast blocks of a bounded number of words; more than MOST_BLOCKS of them are refused, since workers hold them all."""
    most = block_words or BLOCK_WORDS
    spark, out, ids, texts, size = benchmark.sparkSession, [], [], [], 0

    def flush() -> None:
        nonlocal ids, texts, size
        if ids:
            if len(out) == MOST_BLOCKS:
                raise ValueError(f"a benchmark of more than {MOST_BLOCKS * most} words: mark the documents by parts of it")
            out.append(spark.sparkContext.broadcast(index_items(ids, pa.array(texts, pa.string()))))
        ids, texts, size = [], [], 0

    for r in benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("i"), F.coalesce("text", F.lit("")).alias("t")).toLocalIterator():
        ids.append(r.i)
        texts.append(r.t)
        size += len(r.t) // 6 + 1
        if size >= most:
            flush()
    flush()
    return out


def judged(batches: Iterator[pa.RecordBatch], blocks: list[dict], places: bool = False) -> Iterator[pa.RecordBatch]:
    """The rows of batches with the columns of OUT, and with places those of PLACES; a worker's arrays stay as small as chunks are."""
    kind = pa.list_(pa.struct([("item_id", pa.string()), *[(n, pa.int64()) for n in ("item_word", "doc_word", "words")]]))
    names = [n for n, _ in OUT] + [PLACES[0]] * places
    for rows, raw, offs in chunks(batches):
        words, hit, found, where = match(raw, offs, blocks, places)
        new = [
            pa.array(words, pa.int64()),
            pa.array(hit, pa.int64()),
            pa.array([len(f) for f in found], pa.int64()),
            pa.array([hashlib.sha256(",".join(sorted(f)).encode()).hexdigest() for f in found]),
            pa.array((hit > 0) & (20 * hit >= words)),
        ]
        if places:
            new.append(pa.array([[dict(zip(("item_id", "item_word", "doc_word", "words"), m, strict=True)) for m in ms] for ms in where], kind))
        yield pa.RecordBatch.from_arrays([*rows.columns, *new], [*rows.schema.names, *names])


def mark(docs: DataFrame, benchmark: DataFrame, places: bool = False) -> DataFrame:
    """docs with the columns of OUT, and with places also `matches`: every longest verbatim match of WINDOW words or of a whole shorter
    item, as (item_id, word in the item, word in the document, words)."""
    new_columns = [*OUT, PLACES] if places else list(OUT)
    taken = {n for n, _ in new_columns}
    docs = docs.drop(*[c for c in docs.columns if c.lower() in taken])
    schema = T.StructType([*docs.schema.fields, *[T.StructField(n, T._parse_datatype_string(t)) for n, t in new_columns]])
    shared = blocks_of(benchmark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return judged(batches, [b.value for b in shared], places)

    return docs.mapInArrow(run, schema)


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Null and empty texts have no words and are not contaminated; repeated rows are judged alike; an empty benchmark contaminates nothing.

    n_matches and longest_match follow from the matches and their places, which `mark` returns."""
    marked = mark(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"), places=True)
    longest = F.coalesce(F.array_max(F.transform("matches", lambda m: m["words"])), F.lit(0).cast("long"))
    return marked.select("doc_id", *[n for n, _ in OUT], F.size("matches").cast("long").alias("n_matches"), longest.alias("longest_match"))
