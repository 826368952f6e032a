"""Cases where an operator once did less than the whole job."""

import numpy as np
import pytest
from pyspark.sql import functions as F


@pytest.mark.parametrize("n", [2_000, 20_000])
def test_nearest_recall_holds_as_the_table_grows(spark, n):
    from temporal_patterns.llm import permutation_index

    rng = np.random.default_rng(5)
    x = (0.15 * rng.normal(size=(10, 64))[rng.integers(0, 10, n)] + rng.normal(size=(n, 64))).astype(np.float32)
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = permutation_index.nearest(rows, lambda i: F.pmod(i, F.lit(200)) == 0, 5).toPandas()
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    hits = 0
    for q in range(0, n, 200):
        score = unit @ unit[q]
        score[q] = -9
        mine = got[got.query_id == q]
        assert len(mine) == 5
        hits += len(set(np.argsort(-score)[:5]) & set(mine.vec_id))
    assert hits / (5 * len(range(0, n, 200))) >= 0.9


def test_lm_scores_do_not_depend_on_rarity(spark):
    """A word of the least count among 200,000 others is modelled, not taken for the unknown word."""
    from temporal_patterns.llm import lm_scoring

    filler = [(i, " ".join(["x", "y"] * 1000)) for i in range(2, 202)]
    docs = spark.createDataFrame([(0, "rare bird"), (1, "odd fish"), *filler], "doc_id long, text string")
    labels = spark.createDataFrame([(0, 1, 0)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in lm_scoring.score(lm_scoring.fit(docs, labels)).where("doc_id < 2").collect()}
    total, v = 400_004, 7
    p = 2 / (total + v)
    want = -(np.log(p) + np.log(0.4 * p + 0.6)) / 2
    assert got[0].background_entropy == pytest.approx(want) and got[1].background_entropy == pytest.approx(want)
    assert got[0].score < got[1].score < 0  # unseen by the target: 1 / 9 each word by smoothing


def test_copies_of_a_page_keep_their_text(spark):
    from temporal_patterns.llm import html_tree

    div = "<body><div class='content'>the whole story</div></body>"
    own = "<body><article><div id='post-17'>told once</div></article></body>"
    rows = [(i, "http://a/x", div) for i in range(4)] + [(4 + i, "http://b/y", own) for i in range(5)]
    # what four distinct pages of a host share still goes
    rows += [(10 + i, f"http://c/{i}", f"<body><div class='frame'>same words</div><div class='content'>story {i}</div></body>") for i in range(4)]
    got = {r.page_id: r.text for r in html_tree.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert {got[i] for i in range(4)} == {"the whole story"} and {got[4 + i] for i in range(5)} == {"told once"}
    assert [got[10 + i] for i in range(4)] == [f"story {i}" for i in range(4)]
