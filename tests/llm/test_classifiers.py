"""Both learners against plain twins with named features, and what they are worth on texts that they have not seen."""

import math
import re
import zlib

import numpy as np
import pytest

from rolelattice.llm import quality, registry, toxicity

SF = "/root/testdata/sf0.1"
BAD, GOOD = "vile curse rotten filth".split(), "stone river cloud light house table".split()


def corpus(n=120, seed=4):
    r = np.random.default_rng(seed)
    texts, y = [], []
    for k in range(n):
        bad = k % 3 == 0
        words = list(r.choice(GOOD, r.integers(3, 12))) + (list(r.choice(BAD, r.integers(1, 4))) if bad else [])
        r.shuffle(words)
        texts.append(" ".join(words) + (", " if k % 2 else "!"))
        y.append(float(bad))
    return texts, np.array(y)


def logit(p):
    return math.log(p / (1 - p))


def grams(t):
    t = t.lower()
    return {t[i : i + n] for n in (4, 5) for i in range(len(t) - n + 1)}


def scaled_twin(texts, y, probes):
    """Log-count ratios of presence, the features far from independent, a ridge logistic fit by full-batch Adam; features by name."""
    n, n1 = len(y), y.sum()
    count = {}
    for t, v in zip(texts, y, strict=True):
        for g in grams(t):
            c = count.setdefault(g, [0, 0])
            c[int(v)] += 1

    def term(c, m, k):
        return c * math.log(c * n / (m * k)) if c else 0.0

    gain = {g: 2 * (term(p, p + q, n1) + term(q, p + q, n - n1) + term(n1 - p, n - p - q, n1) + term(n - n1 - q, n - p - q, n - n1)) for g, (q, p) in count.items()}
    ratio = {g: math.log((p + 1) / (n1 + 2)) - math.log((q + 1) / (n - n1 + 2)) for g, (q, p) in count.items() if gain[g] >= 12}
    names = sorted(ratio)
    x = np.array([[ratio[g] if g in grams(t) else 0.0 for g in names] for t in texts])
    w, b, m, v, mb, vb = np.zeros(len(names)), logit(y.mean()), 0.0, 0.0, 0.0, 0.0
    for k in range(1, 121):
        e = (1 / (1 + np.exp(-(x @ w + b))) - y) / n
        gw, gb = e @ x + 0.5 * w / n, e.sum()
        m, v, mb, vb = 0.9 * m + 0.1 * gw, 0.99 * v + 0.01 * gw**2, 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb**2
        w = w - 0.02 * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.99**k)) + 1e-8)
        b -= 0.02 * (mb / (1 - 0.9**k)) / (math.sqrt(vb / (1 - 0.99**k)) + 1e-8)
    return [1 / (1 + math.exp(-(sum(w[j] * ratio[g] for j, g in enumerate(names) if g in grams(t)) + b))) for t in probes]


def terms(t):
    words = re.findall(r"[a-z0-9]+|[^a-z0-9\s]+", t.lower())
    count = {}
    for f in [*words, *zip(words, words[1:], strict=False)]:
        count[f] = count.get(f, 0) + 1
    norm = math.sqrt(sum(count.values())) or 1.0
    return {f: math.sqrt(c) / norm for f, c in count.items()}


def ftrl_twin(texts, y, probes, alpha=0.3, beta=1.0, l1=0.02, l2=0.05):
    z, n = {}, {}

    def weight(f, plain=False):
        if plain:
            return -z.get(f, 0.0) / ((beta + math.sqrt(n.get(f, 0.0))) / alpha)
        v = z.get(f, 0.0)
        return 0.0 if abs(v) <= l1 else -(v - math.copysign(l1, v)) / ((beta + math.sqrt(n.get(f, 0.0))) / alpha + l2)

    def margin(t):
        return sum(4 * x * weight(f) for f, x in terms(t).items()) + weight("bias", True)

    order = np.random.default_rng(7)
    for _ in range(3):
        for k in order.permutation(len(texts)):
            e = 1 / (1 + math.exp(-margin(texts[k]))) - y[k]
            for f, x in [*((f, 4 * x) for f, x in terms(texts[k]).items()), ("bias", 1.0)]:
                g, w = e * x, weight(f, f == "bias")
                z[f] = z.get(f, 0.0) + g - (math.sqrt(n.get(f, 0.0) + g * g) - math.sqrt(n.get(f, 0.0))) / alpha * w
                n[f] = n.get(f, 0.0) + g * g
    return [1 / (1 + math.exp(-margin(t))) for t in probes]


@pytest.mark.parametrize("module,twin", [(toxicity, scaled_twin), (quality, ftrl_twin)], ids=["toxicity", "quality"])
def test_learner_equals_its_twin(spark, module, twin):
    texts, y = corpus()
    probes = corpus(40, 9)[0] + ["", "a", "never seen words here"]
    model = module.fit([module.encode(np.frombuffer(t.encode(), np.uint8)) for t in texts], y)
    docs = spark.createDataFrame(list(enumerate(probes)), "doc_id bigint, text string")
    got = {r.doc_id: r.score for r in module.score_all(docs, model).collect()}
    assert [got[i] for i in range(len(probes))] == pytest.approx(twin(texts, y, probes), abs=2e-4)


def area(score, y):
    order = np.argsort(score, kind="stable")
    rank = np.empty(len(y))
    rank[order] = np.arange(1, len(y) + 1)
    pos = y == 1
    return (rank[pos].sum() - pos.sum() * (pos.sum() + 1) / 2) / (pos.sum() * (~pos).sum())


@pytest.mark.parametrize("name,label,least", [("op1_toxicity", "toxic", 0.95), ("op6_quality", "quality", 0.97)])
def test_held_out_texts(spark, name, label, least):
    """Scores of the fold that labels were not learnt from, against its labels."""
    got = {r["doc_id"]: r for r in registry.queries()[name](spark, SF).collect()}
    labels = {r["doc_id"]: r[label] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    held = [i for i in labels if i in got and got[i]["held_out"]]
    assert held and all(zlib.crc32(str(i).encode()) % 4 == 2 for i in held)
    y = np.array([labels[i] for i in held])
    score, predicted = np.array([got[i]["score"] for i in held]), np.array([got[i]["predicted"] for i in held])
    assert area(score, y) >= least
    assert (predicted == y).mean() >= 0.88
