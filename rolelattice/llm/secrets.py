"""Secret scan: the regular expressions of all rules in one minimal deterministic automaton, run over all bytes in a single pass.

Each rule's expression is parsed into a syntax tree over byte sets. Thompson automata of "any prefix, then a rule" are joined,
made deterministic by subset construction and minimised by partition refinement into transition arrays. An accepting state says
which rules have a match that ends at this byte. Where one first does, the rule's reversed automaton, run backwards, gives the
leftmost start, and its own automaton, run on from there, the longest end: non-overlapping leftmost matches per rule.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import chunks, table


@dataclass(frozen=True)
class Rule:
    """A match of pattern must have `least` bytes in all, or (of_value) from its first byte on that ends a match."""

    kind: str
    pattern: str
    least: int
    of_value: bool = False


# The rules.
RULES = (
    Rule("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]+""", 12, True),
    Rule("access", "AKIA[A-Z0-9]+", 18),
    Rule("hex", "[0-9a-f]{16,}", 16),  # of a run, all or nothing: the same as any run with the bound applied afterwards, at fewer hits
    Rule("pem", "-----BEGIN [A-Z ]*PRIVATE KEY-----", 0),
)
BASE = ("assign", "access", "hex")


class Parser:
    """Regular expressions over bytes: literals, \\xHH and escaped signs, sets, groups, (?i:...), alternatives, ? * + {n} {n,} {n,m}."""

    def __init__(self, pattern: str) -> None:
        self.text, self.at, self.fold = pattern, 0, False

    def parse(self) -> tuple:
        tree = self.alternatives()
        if self.at < len(self.text):
            raise ValueError(f"unexpected {self.text[self.at]!r} at {self.at} of {self.text!r}")
        return tree

    def peek(self) -> str:
        return self.text[self.at : self.at + 1]

    def take(self, sign: str) -> bool:
        ok = self.text.startswith(sign, self.at)
        self.at += len(sign) * ok
        return ok

    def alternatives(self) -> tuple:
        parts = [self.sequence()]
        while self.take("|"):
            parts.append(self.sequence())
        return parts[0] if len(parts) == 1 else ("alt", *parts)

    def sequence(self) -> tuple:
        parts = []
        while self.peek() not in ("", "|", ")"):
            parts.append(self.repeated(self.single()))
        return ("cat", *parts)

    def repeated(self, one: tuple) -> tuple:
        while True:
            if self.take("?"):
                one = ("alt", ("cat",), one)
            elif self.take("*"):
                one = ("star", one)
            elif self.take("+"):
                one = ("cat", one, ("star", one))
            elif self.take("{"):
                low, comma, high = self.text[self.at : (end := self.text.index("}", self.at))].partition(",")
                self.at = end + 1
                more = ("star", one) if comma and not high else ("cat", *[("alt", ("cat",), one)] * (int(high) - int(low) if high else 0))
                one = ("cat", *[one] * int(low), more)
            else:
                return one

    def single(self) -> tuple:
        if self.take("(?i:"):
            before, self.fold = self.fold, True
            tree = self.alternatives()
            self.fold = before
        elif self.take("(?:") or self.take("("):
            tree = self.alternatives()
        elif self.take("["):
            return self.chars()
        else:
            return self.bytes_of({self.char()})
        if not self.take(")"):
            raise ValueError(f"unclosed group in {self.text!r}")
        return tree

    def char(self) -> int:
        if self.take("\\x"):
            self.at += 2
            return int(self.text[self.at - 2 : self.at], 16)
        self.take("\\")
        self.at += 1
        return ord(self.text[self.at - 1])

    def chars(self) -> tuple:
        inverted, out = self.take("^"), set()
        while not self.take("]"):
            low = self.char()
            high = low
            if self.peek() == "-" and self.text[self.at + 1] != "]":
                self.at += 1
                high = self.char()
            out |= set(range(low, high + 1))
        return self.bytes_of(set(range(256)) - out if inverted else out)

    def bytes_of(self, values: set[int]) -> tuple:
        if self.fold:
            values |= {c ^ 32 for c in values if chr(c & ~32) in "ABCDEFGHIJKLMNOPQRSTUVWXYZ"}
        return ("set", frozenset(values))


def backwards(tree: tuple) -> tuple:
    if tree[0] == "set":
        return tree
    parts = [backwards(x) for x in tree[1:]]
    return (tree[0], *(reversed(parts) if tree[0] == "cat" else parts))


@dataclass
class Automaton:
    """next[state, class of byte]; accepts[state]: bit r if a match of rule r ends here. States from `first` on accept; state `dead`, if any, leads nowhere."""

    classes: np.ndarray
    next: np.ndarray
    accepts: np.ndarray
    first: int
    dead: int


def compile_trees(trees: list[tuple], anywhere: bool) -> Automaton:
    """One minimal automaton of all trees; with `anywhere` a match may begin at every byte, else at the first only."""
    eps: list[list[int]] = []
    move: list[list[tuple[frozenset, int]]] = []

    def state() -> int:
        eps.append([])
        move.append([])
        return len(eps) - 1

    def build(node: tuple, a: int) -> int:
        kind, *parts = node
        if kind == "set":
            b = state()
            move[a].append((parts[0], b))
            return b
        if kind == "cat":
            for p in parts:
                a = build(p, a)
            return a
        if kind == "alt":
            end = state()
            for p in parts:
                s = state()
                eps[a].append(s)
                eps[build(p, s)].append(end)
            return end
        hub = state()  # star
        eps[a].append(hub)
        eps[build(parts[0], hub)].append(hub)
        return hub

    root = state()
    final: dict[int, int] = {}
    for r, tree in enumerate(trees):
        s = state()
        eps[root].append(s)
        final[build(tree, s)] = r
    # bytes that no set tells apart share a class
    sets = list({m[0] for ms in move for m in ms})
    marks: dict[tuple, int] = {}
    classes = np.array([marks.setdefault(tuple(c in s for s in sets), len(marks)) for c in range(256)], np.uint8)
    member = {k: int(np.flatnonzero(classes == k)[0]) for k in range(len(marks))}

    @cache
    def reach(s: int) -> frozenset:
        todo, out = [s], {s}
        while todo:
            for t in eps[todo.pop()]:
                if t not in out:
                    out.add(t)
                    todo.append(t)
        return frozenset(x for x in out if move[x] or x in final)

    after = [[frozenset().union(*[reach(t) for on, t in move[s] if member[k] in on]) for k in range(len(marks))] for s in range(len(eps))]
    start = reach(root)
    ids, todo, rows, acc = {start: 0}, [start], [], []
    for now in todo:  # grows while subsets are found
        acc.append(sum(1 << final[s] for s in now if s in final))
        row = []
        for k in range(len(marks)):
            to = frozenset().union(*[after[s][k] for s in now], start if anywhere else ())
            if to not in ids:
                ids[to] = len(ids)
                todo.append(to)
            row.append(ids[to])
        rows.append(row)
    table_, accepts = np.array(rows), np.array(acc)
    block = np.unique(accepts, return_inverse=True)[1]
    while True:  # refine until no block splits
        new = np.unique(np.column_stack([block, block[table_]]), axis=0, return_inverse=True)[1].reshape(-1)
        if new.max() == block.max():
            break
        block = new
    # start state first, accepting states last
    keep = np.unique(block, return_index=True)[1]
    order = sorted(keep, key=lambda s: (accepts[s] != 0, block[s] != block[0], s))
    name = np.empty(len(keep), np.int32)
    for new_id, s in enumerate(order):
        name[block[s]] = new_id
    nxt, out = np.array([name[block[table_[s]]] for s in order], np.int32), accepts[order]
    stuck = np.flatnonzero((nxt == np.arange(len(nxt))[:, None]).all(1) & (out == 0))
    return Automaton(classes, nxt, out, int((out == 0).sum()), int(stuck[0]) if len(stuck) and not anywhere else -1)


@dataclass
class Compiled:
    """All rules together, and each alone forwards and backwards; rules must not match the empty text."""

    rules: tuple[Rule, ...]
    all: Automaton
    ahead: list[Automaton]
    back: list[Automaton]


@cache
def compile_rules(rules: tuple[Rule, ...] = RULES) -> Compiled:
    trees = [Parser(r.pattern).parse() for r in rules]
    return Compiled(rules, compile_trees(trees, True), [compile_trees([t], False) for t in trees], [compile_trees([backwards(t)], False) for t in trees])


def scan(raw: np.ndarray, auto: Automaton, lanes: int = 2048) -> tuple[np.ndarray, np.ndarray]:
    """Byte positions where an accepting state is entered, and that state, from the start state at raw[0].

    The buffer is cut into lanes that step together, each from the start state; then each lane whose true first state
    differs is stepped again until both runs agree.
    """
    n, wide = len(raw), auto.next.shape[1]
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int32)
    cols = max(64, -(-n // lanes))
    lanes = -(-n // cols)
    codes = np.full(lanes * cols, auto.classes[0], np.uint8)
    codes[:n] = auto.classes[raw]
    grid = np.ascontiguousarray(codes.reshape(lanes, cols).T)
    flat = (auto.next * wide).astype(np.int32).ravel()
    state, edge = np.zeros(lanes, np.int32), auto.first * wide
    pos, got = [], []
    for j in range(cols):
        state = flat[state + grid[j]]
        hit = np.flatnonzero(state >= edge)
        if len(hit):
            pos.append(hit * cols + j)
            got.append(state[hit])
    at = np.concatenate(pos) if pos else np.zeros(0, np.int64)
    st = np.concatenate(got) if got else np.zeros(0, np.int32)
    order = np.argsort(at, kind="stable")
    at, st = at[order], st[order]
    # mend: the true state at a lane's start is the end state of the lane before
    drop, more = [], []
    true = 0
    for k in range(lanes):
        end = state[k]
        if true:
            a, b, j = true, 0, k * cols
            stop = min(n, j + cols)
            while a != b and j < stop:
                a, b = flat[a + codes[j]], flat[b + codes[j]]
                if a != b:
                    if b >= edge:
                        drop.append(j)
                    if a >= edge:
                        more.append((j, a))
                j += 1
            if a != b:
                end = a
        true = end
    if drop or more:
        keep = ~np.isin(at, drop)
        at = np.concatenate([at[keep], np.array([m[0] for m in more], np.int64)])
        st = np.concatenate([st[keep], np.array([m[1] for m in more], np.int32)])
        order = np.argsort(at, kind="stable")
        at, st = at[order], st[order]
    inside = at < n
    return at[inside], st[inside] // wide


def farthest(auto: Automaton, data: bytes, places: range) -> int:
    """The last of the places at which the automaton, fed with their bytes, accepts (-1: none)."""
    state, best = 0, -1
    for i in places:
        state = auto.next[state, auto.classes[data[i]]]
        if state >= auto.first:
            best = i
        elif state == auto.dead:
            break
    return best


class Scanner:
    def __init__(self, compiled: Compiled | None = None) -> None:
        self.compiled = compiled or compile_rules()
        self.rules, self.auto = self.compiled.rules, self.compiled.all

    def spans(self, raw: np.ndarray, offs: np.ndarray) -> list[list[tuple[int, str, int]]]:
        """Per row: (start, kind, end) in bytes from the row's first byte."""
        n = len(raw)
        # a byte that no rule reads between rows keeps matches inside them
        rows = len(offs) - 1
        joined = np.zeros(n + rows, np.uint8)
        joined[np.arange(n) + np.repeat(np.arange(rows), np.diff(offs))] = raw
        base = offs + np.arange(rows + 1)
        out: list[list] = [[] for _ in range(rows)]
        at, state = scan(joined, self.auto)
        bits = self.auto.accepts[state]
        whole = joined.tobytes()
        for r, rule in enumerate(self.rules):
            here = at[(bits >> r & 1) == 1]
            done = k = 0
            while k < len(here):
                e = int(here[k])
                row = int(np.searchsorted(base, e, "right")) - 1
                low, high = int(base[row]), int(base[row + 1]) - 1
                s = farthest(self.compiled.back[r], whole, range(e, max(done, low) - 1, -1))
                if s < 0:  # what ends here began within the match before
                    k += 1
                    continue
                done = farthest(self.compiled.ahead[r], whole, range(s, high)) + 1
                if done - (e if rule.of_value else s) >= rule.least:
                    out[row].append((s - low, rule.kind, done - low))
                k = int(np.searchsorted(here, done))
        place = {rule.kind: i for i, rule in enumerate(self.rules)}
        for found in out:
            found.sort(key=lambda x: (x[0], place[x[1]]))
        return out


def to_code_points(raw: np.ndarray, found: list[tuple[int, str, int]]) -> list[tuple[int, str, int]]:
    """Byte offsets become code point offsets."""
    if not found:
        return found
    points = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
    return [(int(points[s]), kind, int(points[e])) for s, kind, e in found]


SPANS = T.StructType([T.StructField("_spans", T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("kind", T.StringType()), T.StructField("end", T.LongType())])))])


def find(docs: DataFrame, name: str = "_spans") -> DataFrame:
    """docs with an array of (start, kind, end), code points of the whole text, end exclusive; a null text has none."""
    docs = docs.drop(name)
    schema = T.StructType([*docs.schema.fields, T.StructField(name, SPANS[0].dataType)])

    compiled = compile_rules()  # once, on the driver; tasks get its arrays

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(compiled)
        kind = pa.list_(pa.struct([("start", pa.int64()), ("kind", pa.string()), ("end", pa.int64())]))
        for rows, raw, offs in chunks(batches):
            spans = [[{"start": s, "kind": k, "end": e} for s, k, e in to_code_points(raw[offs[i] : offs[i + 1]], f)] for i, f in enumerate(scanner.spans(raw, offs))]
            yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(spans, kind)], [*rows.schema.names, name])

    return docs.mapInArrow(run, schema)


def _join(spans: F.Column) -> F.Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(docs: DataFrame, mask: str = "[secret]") -> DataFrame:
    """docs with every span of a secret replaced (spans that overlap count as one) and n_chars following the text."""
    kept = docs.columns
    schema = docs.schema

    compiled = compile_rules()  # once, on the driver; tasks get its arrays

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(compiled)
        for rows, raw, offs in chunks(batches):
            at = rows.schema.get_field_index("text")
            texts, n_at = rows.column(at).to_pylist(), rows.schema.get_field_index("n_chars")
            counts = rows.column(n_at).to_pylist() if n_at >= 0 else None
            for i, found in enumerate(scanner.spans(raw, offs)):
                if found:
                    b, out, done = raw[offs[i] : offs[i + 1]].tobytes(), [], 0
                    for s, _, e in found:
                        if s >= done:
                            out += [b[done:s], mask.encode()]
                        done = max(done, e)
                    texts[i] = b"".join([*out, b[done:]]).decode("utf-8", "replace")
                    if counts is not None:
                        counts[i] = len(texts[i])
            cols = list(rows.columns)
            cols[at] = pa.array(texts, rows.schema.field(at).type)
            if counts is not None:
                cols[n_at] = pa.array(counts, rows.schema.field(n_at).type)
            yield pa.RecordBatch.from_arrays(cols, rows.schema.names)

    return docs.mapInArrow(run, schema).select(*kept)


def op2_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Null and empty texts have no spans and the digest of the empty string; repeated rows give repeated results."""
    found = find(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("text")
    base = F.filter("_spans", lambda s: s["kind"].isin(*BASE))
    count = lambda k: F.size(F.filter("_spans", lambda s: s["kind"] == k)).cast("long")
    return found.select("doc_id", *[count(k).alias(f"n_{k}") for k in BASE], F.sha2(_join(base).cast("binary"), 256).alias("base_sha256"), _join(F.col("_spans")).alias("spans"))


def by_regex(s: str) -> list[tuple[int, str, int]]:
    """Brute force for tests: the base rules by the regular expression library."""
    import re

    out = []
    for kind, pattern, group, least in (
        ("assign", r"""([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 12),
        ("access", "AKIA[A-Z0-9]+", 0, 18),
        ("hex", "[0-9a-f]+", 0, 16),
    ):
        out += [(m.start(), kind, m.end()) for m in re.finditer(pattern, s) if len(m[group]) >= least]
    return sorted(out, key=lambda x: (x[0], BASE.index(x[1])))


def digest(found: list[tuple[int, str, int]]) -> str:
    return hashlib.sha256(",".join(f"{k}:{s}:{e}" for s, k, e in found if k in BASE).encode()).hexdigest()
