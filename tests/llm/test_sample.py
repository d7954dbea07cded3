"""The classifiers are fitted on whole texts of the sampled rows."""

import zlib

from rolelattice.llm import quality, toxicity

LONG = "plain words of no harm at all " * 500  # over 12,000 characters
IDS = [i for i in range(200) if zlib.crc32(str(i).encode()) % 4 != 2]


def tables(spark, texts):
    docs = spark.createDataFrame(list(zip(IDS, texts, strict=False)), "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, int("vile" in t), int("vile" not in t)) for i, t in zip(IDS, texts, strict=False)], "doc_id bigint, toxic int, quality int")
    return docs, labels


def test_the_end_of_a_long_text_is_learnt(spark):
    texts = [f"{LONG} {'vile curse' if k % 2 else 'kind'} number {k}" for k in range(60)]
    docs, labels = tables(spark, texts)
    probe = spark.createDataFrame([(1, "vile curse"), (2, "kind number")], "doc_id bigint, text string")
    for m, label, up in ((toxicity, "toxic", 1), (quality, "quality", 2)):
        got = {r.doc_id: r.score for r in m.score_all(probe, m.fit_labelled(docs, labels, label)).collect()}
        assert got[up] > got[3 - up]


def test_repeats_are_whole_texts_and_do_not_shrink_the_sample(spark):
    texts = ["one same text"] * 20 + [f"{LONG} end {k}" for k in range(20)]
    docs, labels = tables(spark, texts)
    for m, label in ((toxicity, "toxic"), (quality, "quality")):
        for rows, want in ((100, 21), (15, 15)):
            got, y = toxicity.sample(docs, labels, label, rows, m.encode)
            assert len(got) == len(y) == want and len(set(got)) == want


def test_encoding_keeps_all_features():
    import numpy as np

    for n in (0, 3, 100, 60_000):
        raw = np.random.default_rng(n).integers(32, 127, n).astype(np.uint8)
        want = np.unique(np.concatenate(toxicity.gram_ids(raw, toxicity.lower_table())))
        assert toxicity.decode(toxicity.encode(raw)).tolist() == want.tolist()
