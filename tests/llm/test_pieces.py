"""Parts of the text operators against brute force."""

import math
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rolelattice.llm import decontamination, html, packing, secrets, suffix_dedup, suffixes, topk

SCANNER = secrets.Scanner()
BITS = ["password", "PassWd", "secret", "token", "api_key", '"', "'", " ", ":", "=", "AKIA", "AKIAAB12CD34", "deadbeef", "0123456789abcdef", "é", "x", "\n", "abcdefghijkl", "+/", "."]


def offsets(parts):
    return np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)


def buffer(parts):
    return np.frombuffer(b"".join(parts), np.uint8)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.lists(st.sampled_from(BITS), max_size=20).map("".join), min_size=1, max_size=6))
def test_scanner_equals_regular_expressions(texts):
    parts = [t.encode() for t in texts]
    raw, offs = buffer(parts), offsets(parts)
    got = SCANNER.spans(raw, offs)
    for i, t in enumerate(texts):
        assert [x for x in secrets.to_code_points(raw[offs[i] : offs[i + 1]], got[i]) if x[1] in secrets.BASE] == secrets.by_regex(t)


@pytest.mark.parametrize("pattern", ["a(b|cd)*e", "(?i:ab?c)x{2,3}", r"\x41[^b-d]+z", "(?:ab|a)(c|bcd)+", "x{3}|y{2,}"])
def test_automata_equal_regular_expressions(pattern):
    r = random.Random(3)
    one = secrets.Compiled((secrets.Rule("r", pattern, 0),), *[secrets.compile_rules((secrets.Rule("r", pattern, 0),)).__dict__[k] for k in ("all", "ahead", "back")])
    for _ in range(300):
        t = "".join(r.choice("abcdexyzAB") for _ in range(r.randint(0, 14)))
        whole = [bool(re.fullmatch(pattern, t[:k])) for k in range(len(t) + 1)]
        last = max((k for k in range(1, len(t) + 1) if whole[k]), default=0)
        assert secrets.farthest(one.ahead[0], t.encode(), range(len(t))) + 1 == last
        ends = {k for k in range(1, len(t) + 1) if any(re.fullmatch(pattern, t[i:k]) for i in range(k))}
        at, state = secrets.scan(buffer([t.encode()]), one.all)
        assert set((at + 1).tolist()) == ends


def test_scanner_finds_key_headers_and_is_minimal():
    t = b"x -----BEGIN RSA PRIVATE KEY----- y"
    assert SCANNER.spans(buffer([t]), offsets([t])) == [[(2, "pem", 33)]]
    a = SCANNER.auto
    assert (a.accepts[: a.first] == 0).all() and (a.accepts[a.first :] != 0).all()


@settings(max_examples=60, deadline=None)
@given(st.binary(max_size=60), st.integers(1, 3))
def test_suffix_array_and_common_prefixes(data, small):
    buf = np.frombuffer(bytes(b % (small + 1) + 97 for b in data), np.uint8)
    n = len(buf)
    ends = np.full(n, n)
    order = suffixes.refine(suffixes.words8(buf), 8, n + 8, ends)
    text = buf.tobytes()
    assert order.tolist() == sorted(range(n), key=lambda i: text[i:])
    lcp = suffixes.kasai(buf, order, ends, 40, lanes=3)
    for k in range(1, n):
        a, b = text[order[k - 1] :], text[order[k] :]
        m = next((i for i in range(min(len(a), len(b))) if a[i] != b[i]), min(len(a), len(b)))
        assert lcp[k] == min(m, 40)


def naive_starts(texts, n):
    count = {}
    for t in texts:
        for i in range(len(t) - n + 1):
            count[t[i : i + n]] = count.get(t[i : i + n], 0) + 1
    return [[count[t[i : i + n]] > 1 for i in range(len(t) - n + 1)] for t in texts]


@pytest.mark.parametrize("part", [None, 3000])
def test_repeated_windows_within_and_across_parts(part):
    r = random.Random(5)
    base = bytes(r.choice(b"abcdef ") for _ in range(900))
    texts = [base[r.randint(0, 300) : r.randint(600, 900)] + bytes(r.choice(b"xyz") for _ in range(r.randint(0, 200))) for _ in range(12)]
    texts += [b"a" * 950, b"short"]
    assert [f.tolist() for f in suffix_dedup.repeated(texts, part)] == naive_starts(texts, suffix_dedup.LENGTH)


def test_longest_match():
    parts = [b"the quick brown fox jumps", b"a quick brown cat"]
    assert decontamination.longest_match(buffer(parts), offsets(parts), "quick brown fox sleeps") == (3, [(0, 1)])
    assert decontamination.longest_match(buffer(parts), offsets(parts), "Quick BROWN") == (2, [(0, 1), (1, 1)])


@settings(max_examples=25, deadline=None)
@given(st.dictionaries(st.integers(1, 64), st.integers(1, 40), max_size=20))
def test_cutting_stock_holds_the_demand(counts):
    d = np.zeros(64, np.int64)
    for k, v in counts.items():
        d[k - 1] = v
    got = packing.solve(d, 64)
    assert sum((n * p for p, n in got), np.zeros(64, np.int64)).tolist() == d.tolist()
    assert all((p * np.arange(1, 65)).sum() <= 64 for p, _ in got)


def least_sequences(demand, capacity):
    """A lower bound: duals of the program are feasible if no pattern is worth more than one sequence; the best of two simple families."""
    size = np.arange(1, len(demand) + 1)
    best = math.ceil((demand * size).sum() / capacity)
    for k in range(1, capacity // 2 + 1):  # pieces over capacity - k fill a sequence, those under k are free, others half of one or by size
        big, mid = size > capacity - k, (size >= k) & (size <= capacity - k)
        best = max(best, demand[big].sum() + math.ceil((demand * size)[mid].sum() / capacity), demand[size > capacity // 2].sum())
    return best


def test_inverse():
    r = np.random.default_rng(2)
    a = np.triu(r.integers(1, 5, (60, 60)).astype(float))[r.permutation(60)]
    np.testing.assert_allclose(np.einsum("ij,jk->ik", packing.inverted(a), a), np.eye(60), atol=1e-8)


def test_cutting_stock_wastes_little():
    for d, capacity in ((np.random.default_rng(1).integers(0, 300, 128), 128), (np.r_[np.random.default_rng(2).integers(0, 900, 40), np.zeros(88, np.int64)], 128)):
        used = sum(n for _, n in packing.solve(d, capacity))
        assert used <= 1.01 * least_sequences(d, capacity) + 2
    # sixes stand alone, threes go by two
    assert sum(n for _, n in packing.solve(np.array([0, 0, 50, 0, 0, 70, 0, 0]), 8)) == 95


def test_ids_are_those_of_whole_texts():
    from tokenizers import Tokenizer

    t, ids = Tokenizer.from_file(packing.tokenizer_path()), packing.Ids(packing.tokenizer_path())
    texts = ["It's a Test!! don't 3x5", "éÉ*** ΑΣ. ΑΣ a<|endoftext|>b", "", " \n\t ", "x\x1cy ź", "UPPER,lower;Mixed|"]
    for x, got in zip(texts, ids.of_all([x.encode() for x in texts]), strict=True):
        assert np.frombuffer(got, "<u4").tolist() == t.encode(x, add_special_tokens=False).ids


def test_block_search_prunes_and_stays_exact():
    r = np.random.default_rng(2)
    v = np.floor(1024 * r.normal(size=(4000, 8)) * np.repeat(r.random(16) ** 4 * 3, 250)[:, None])
    ids, q = np.arange(4000), v[::400]
    best, counters = topk.Best(len(q), 10), {}
    topk.search_blocks(ids[::400], q, ids, v, best, counters)
    for i, x in enumerate(q):
        s = v @ x
        order = [j for j in np.lexsort((ids, -s)) if j != ids[::400][i]][:10]
        assert best.id[i].tolist() == order and best.score[i].tolist() == s[order].tolist()
    assert counters["scored"] < counters["blocks"]


PAGE = """<html><head><title>t</title><style>p{}</style><script>var a="</p>";</script></head><body><header>top</header><nav><ul><li>menu</ul></nav>
<div class="cookie-notice">we use cookies</div><div class="wrap"><article class="post-17"><h1>Head &amp; line</h1><p>One
 two&nbsp;three<p>Four <b>five</b>, <a href="x">six</a>.<br>seven<ul><li>item a<li>item b</ul><div class="ad">buy</div><form>mail</form>
<section class="comments"><p>great post</p></section></article><aside>side</aside></div><footer>end</footer></body></html>"""


def test_main_text_of_a_page():
    want = "Head & line\n\nOne two three\n\nFour five, six. seven\n\nitem a\n\nitem b"
    path, score = html.candidate(html.blocks(PAGE))
    assert path.endswith("article.post-#") and score > 0
    assert html.main_text(PAGE, path) == html.main_text(PAGE, None) == html.main_text(PAGE, ">html>body>none") == want
    assert html.main_text("", None) == "" and html.main_text("<p>a < b", None) == "a < b"


def test_arrow_buffers_with_nulls_and_slices():
    from rolelattice.llm.common import utf8

    a = pa.array(["ab", None, "", "çd"]).slice(1)
    raw, offs = utf8(a)
    assert raw.tobytes() == "çd".encode() and offs.tolist() == [0, 0, 0, 3]
