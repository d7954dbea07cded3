"""Packing by cutting-stock column generation over the histogram of piece lengths.

A document is cut into full sequences and one remainder, so pieces' lengths, and with them the linear program, are bounded
by the sequence length whatever the input. The program's columns are patterns (how many pieces of each length class share a
sequence); a knapsack over the duals prices new ones. Patterns are used a whole number of times, what rounding leaves
over (at most one sequence for each pattern) is packed by falling length, and each class's ranked pieces fill its places.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import filterfalse, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import chunks, cut, number, own, table

SEQUENCE = 2048
#: Lengths are rounded up to multiples of this in the program.
STEP = 4
END_ID = 1
#: Distinct words whose ids a worker keeps.
CACHE_WORDS = 800_000
#: Punctuation that this tokenizer keeps apart from the letters before it (an apostrophe may join them).
_MARKS = b"!#$%&*,.:;?|"
#: Letters up to U+00FF that normal forms replace.
_FOLDED = frozenset("\xaa\xb5\xba")

PIECES = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint"


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class Ids(dict):
    """Word -> its ids as little-endian 32-bit bytes. Words are what ASCII white space separates; this tokenizer never joins across it.

    It splits punctuation from letters and lowers letters, too, so that most unseen words are put together from seen ones."""

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)

    @staticmethod
    def of_worker(path: str) -> Ids:
        """One instance for all tasks that a worker process runs, until it runs another operator's."""
        held = own("packing")
        if path not in held:
            held[path] = Ids(path)
        return held[path]

    @staticmethod
    def plain(text: str) -> bool:
        """Letters of the first two Unicode blocks without those that stand for others: their lower case is one letter each."""
        return text.isalpha() and (text.isascii() or max(text) <= "\xff" and not _FOLDED.intersection(text))

    def parts_of(self, word: bytes) -> tuple[bytes, bytes]:
        """The letters that are looked up for a word, and the punctuation after them; (word, nothing) for other words."""
        core = word.rstrip(_MARKS)
        if core.isascii():
            if core.isalpha():
                return core.lower(), word[len(core) :]
        elif self.plain(t := core.decode("utf-8", "replace")):
            return t.lower().encode(), word[len(core) :]
        return word, b""

    def learn(self, words: set[bytes]) -> None:
        """Encode what is not known yet: words of letters in one text, in which each is one pre-token; others one by one."""
        made = {w: self.parts_of(w) for w in words}
        new = {p for both in made.values() for p in both if p and p not in self}
        letters = [w for w in new if self.plain(w.decode("utf-8", "replace"))]
        for at in range(0, len(letters), 2000):
            some = letters[at : at + 2000]
            e = self.tokenizer.encode(b" ".join(some).decode(), add_special_tokens=False)
            ids, word = np.array(e.ids, "<u4"), np.array(e.word_ids)
            edge = np.append(np.flatnonzero(np.append(True, word[1:] != word[:-1])), len(ids))
            if len(edge) - 1 != len(some):
                raise RuntimeError("a word was split before encoding")
            data = ids.tobytes()
            for w, i, j in zip(some, edge[:-1].tolist(), edge[1:].tolist(), strict=True):
                self[w] = data[4 * i : 4 * j]
        rest = sorted(new.difference(letters))
        for w, e in zip(rest, self.tokenizer.encode_batch_fast([w.decode("utf-8", "replace") for w in rest], add_special_tokens=False), strict=True):
            self[w] = np.array(e.ids, "<u4").tobytes()
        for w, (core, tail) in made.items():
            if w not in self:
                self[w] = self[core] + self[tail] if tail else self[core]

    def of_all(self, texts: list[bytes]) -> list[bytes]:
        if len(self) > CACHE_WORDS:  # the words seen first are the common ones
            first = list(islice(self.items(), CACHE_WORDS // 2))
            self.clear()
            self.update(first)
        words = [t.split() for t in texts]
        new: set[bytes] = set()
        for w in words:
            new.update(filterfalse(self.__contains__, w))
        self.learn(new)
        return [b"".join(map(self.__getitem__, w)) for w in words]


def pieces(docs: DataFrame, path: str, sequence: int = SEQUENCE) -> DataFrame:
    """Each document's ids and the end id, cut at multiples of the sequence length. A null text is an empty one: the end id alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        ids, end = Ids.of_worker(path), np.array([END_ID], "<u4").tobytes()
        for rows, raw, offs in chunks(batches, operator="packing"):
            out: list[list] = [[], [], [], [], []]
            body = raw.tobytes()
            texts = [body[a:b] for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
            for doc, got in zip(rows.column(0).to_pylist(), ids.of_all(texts), strict=True):
                got += end
                n = len(got) // 4
                for s in range(0, n, sequence):
                    part = got[4 * s : 4 * (s + sequence)]
                    for col, v in zip(out, (doc, s, len(part) // 4, zlib.crc32(part), n), strict=True):
                        col.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, PIECES)


def knapsack(values: np.ndarray, capacity: int) -> tuple[float, np.ndarray]:
    """Most valuable multiset of classes (class i has size i + 1) within capacity; values <= 0 are never taken."""
    use = np.flatnonzero(values > 1e-12)
    best, pick = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    size, worth = use + 1, values[use]
    fits = np.searchsorted(size, np.arange(capacity + 1), "right")
    for c in range(1, capacity + 1):
        best[c] = best[c - 1]
        if k := fits[c]:
            got = best[c - size[:k]] + worth[:k]
            j = int(got.argmax())
            if got[j] > best[c] + 1e-12:
                best[c], pick[c] = got[j], use[j]
    counts, c = np.zeros(len(values), np.int64), capacity
    while c > 0:
        if pick[c] < 0:
            c -= 1
        else:
            counts[pick[c]] += 1
            c -= int(pick[c]) + 1
    return float(best[capacity]), counts


def first_basis(left: np.ndarray, size: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Patterns filled by falling size, each used until one of its classes is exhausted. That class is in no later pattern,
    so in order of exhaustion the patterns are triangular; a class exhausted beside another gets a pattern of its own, unused."""
    m = len(left)
    left, columns, x = left.copy(), np.zeros((m, m)), np.zeros(m)
    while (left > 0).any():
        p, room = np.zeros(m), capacity
        for i in np.flatnonzero(left > 0)[::-1]:
            if size[i] <= room:
                p[i] = max(1, min(room // size[i], int(left[i])))
                room -= int(p[i]) * int(size[i])
                if not room:
                    break
        used = np.flatnonzero(p)
        n = (left[used] / p[used]).min()
        gone = used[left[used] <= n * p[used] + 1e-9]
        left -= n * p
        left[gone] = 0
        columns[:, gone[0]], x[gone[0]] = p, n
        for i in gone[1:]:
            columns[i, i] = capacity // size[i]
    return columns, x


def inverted(a: np.ndarray) -> np.ndarray:
    """The inverse by elimination in plain array operations: threads of a linear algebra library that was loaded before the
    JVM was forked off can wait forever on a driver."""
    n = len(a)
    work = np.concatenate([a.astype(float), np.eye(n)], axis=1)
    for k in range(n):
        p = k + int(np.abs(work[k:, k]).argmax())
        if p != k:
            work[[k, p]] = work[[p, k]]
        work[k] /= work[k, k]
        rows = np.flatnonzero(work[:, k])
        rows = rows[rows != k]
        work[rows] -= work[rows, k][:, None] * work[k]
    return work[:, n:]


def solve(demand: np.ndarray, capacity: int, gap: float = 2e-3, rounds: int = 4000) -> list[tuple[np.ndarray, int]]:
    """Patterns with whole numbers of uses that together hold exactly `demand` (pieces of class i have size i + 1)."""
    have = np.flatnonzero(demand > 0)
    if not len(have):
        return []
    m = len(have)
    size = have + 1
    columns, x = first_basis(demand[have].astype(float), size, capacity)
    inverse = inverted(columns)
    center, bound = size / capacity, float(demand[have] @ size) / capacity  # duals that are feasible, and the sequences they prove necessary
    blend = 0.8
    for _ in range(rounds):
        if x.sum() <= bound * (1 + gap):
            break
        dual = inverse.sum(0)  # each pattern costs one sequence
        for share in (blend, 0.0):  # prices near the best proven duals keep the program from wandering; the plain ones settle it
            prices = share * center + (1 - share) * dual
            values = np.zeros(capacity)
            values[have] = prices
            worth, counts = knapsack(values, capacity)
            if (proven := float(demand[have] @ np.maximum(prices, 0)) / max(worth, 1e-12)) > bound:
                center, bound = np.maximum(prices, 0) / worth, proven
            if gain := dual @ counts[have] > 1 + 1e-9:
                break
        if not gain:
            break
        a = counts[have].astype(float)
        d = np.einsum("ij,j->i", inverse, a)
        pos = d > 1e-9
        ratio = np.where(pos, x / np.where(pos, d, 1), np.inf)
        out = int(ratio.argmin())
        step = ratio[out]
        x -= step * d
        x[out] = step
        row = inverse[out] / d[out]
        inverse -= np.outer(d, row)
        inverse[out] = row
        columns[:, out] = a
    uses = np.floor(np.maximum(x, 0) + 1e-9).astype(np.int64)
    left = demand.astype(np.int64).copy()
    result = []
    for j in np.flatnonzero(uses):
        p = np.zeros(capacity, np.int64)
        p[have] = np.round(columns[:, j]).astype(np.int64)
        n = int(min(uses[j], (left[p > 0] // p[p > 0]).min()))
        if n > 0:
            left -= n * p
            result.append((p, n))
    # the rest by falling size, each into the fullest sequence that has room
    room: list[list[np.ndarray]] = [[] for _ in range(capacity + 1)]
    opened = []
    for i in np.flatnonzero(left)[::-1]:
        for _ in range(int(left[i])):
            r = next((r for r in range(int(i) + 1, capacity + 1) if room[r]), None)
            p = room[r].pop() if r else np.zeros(capacity, np.int64)
            if r is None:
                opened.append(p)
            p[i] += 1
            room[(r or capacity) - int(i) - 1].append(p)
    return result + [(p, 1) for p in opened]


def places(patterns: list[tuple[np.ndarray, int]], capacity: int) -> dict[int, tuple[np.ndarray, ...]]:
    """Per class: first ranks, first sequence and pieces a sequence of each pattern that uses it."""
    per: dict[int, list] = {}
    first = 0
    for p, n in patterns:
        for i in np.flatnonzero(p):
            per.setdefault(int(i) + 1, []).append((n * int(p[i]), first, int(p[i])))
        first += n
    return {c: (np.concatenate([[0], np.cumsum([x[0] for x in v])[:-1]]), np.array([x[1] for x in v]), np.array([x[2] for x in v])) for c, v in per.items()}


def pack(cut_pieces: DataFrame, sequence: int = SEQUENCE, step: int = STEP) -> DataFrame:
    """cut_pieces (with a column length) with sequence_id and offset."""
    spark, capacity = cut_pieces.sparkSession, sequence // step
    rows = cut_pieces.withColumn("_class", F.ceil(F.col("length") / step).cast("int"))
    demand = np.zeros(capacity, np.int64)
    for r in rows.groupBy("_class").count().collect():  # at most `capacity` rows
        demand[r["_class"] - 1] = r["count"]
    shared = spark.sparkContext.broadcast(places(solve(demand, capacity), capacity))
    ranked = number(rows, "_class", "_rank")

    @F.pandas_udf("sequence_id bigint, nth int")
    def put(cls, rank):  # noqa: ANN001, ANN202
        import pandas as pd

        seq, nth = np.zeros(len(cls), np.int64), np.zeros(len(cls), np.int32)
        for c in cls.unique():
            first, base, each = shared.value[int(c)]
            here = np.flatnonzero(cls.to_numpy() == c)
            t = rank.to_numpy()[here]
            e = np.searchsorted(first, t, "right") - 1
            seq[here], nth[here] = base[e] + (t - first[e]) // each[e], (t - first[e]) % each[e]
        return pd.DataFrame({"sequence_id": seq, "nth": nth})

    put_ = ranked.withColumn("_p", put("_class", "_rank")).withColumn("sequence_id", F.col("_p.sequence_id"))
    before = Window.partitionBy("sequence_id").orderBy(F.desc("_class"), "_p.nth").rowsBetween(Window.unboundedPreceding, -1)
    return put_.withColumn("offset", F.coalesce(F.sum("length").over(before), F.lit(0)).cast("long")).select(*cut_pieces.columns, "sequence_id", "offset")


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Null and empty texts are one piece of one id; repeated rows are pieces of their own; an empty table gives no rows."""
    return pack(cut(pieces(table(spark, sf_dir, "documents"), tokenizer_path())))
