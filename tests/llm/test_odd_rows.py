"""Nulls, empty and blank texts, repeated rows, clashing columns, empty tables."""

import public_tokenizers
import pytest

from temporal_patterns.llm import byte_bpe, html_tree, line_dedup, lm_scoring, mixing, permutation_index, quality, suffix_doubling, token_counts
from pyspark.sql import functions as F

ROWS = [(1, None, None, 1), (2, "", "a", 2), (3, " \t\n", "b", 3), (None, "one two three four five six\n" * 12, "a", 4), (5, "z " * 400, "b", 5), (5, "z " * 400, "b", 5), (6, "one two three four five six\nown words", None, 6)]


CLASHING = ["k", "th", "__k", "__th", "__start", "__length", "__parts", "__size", "__copy", "__lap", "__uid", "__removed", "__host", "__salt", "row", "starts", "id", "component", "key", "n"]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, "doc_id long, text string, source string, score long").withColumns({c: F.lit(c) for c in CLASHING})


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(None, 1, 0), (6, 1, None), (5, None, 0)], "doc_id long, quality int, toxic int")


OPERATORS = {
    "mixing": lambda d, lab: mixing.mix_documents(d),
    "quality": quality.assess,
    "tokens": lambda d, lab: token_counts.count_documents(d, public_tokenizers.path("byte_bpe_50k.json")),
    "lines": lambda d, lab: line_dedup.drop_repeated_lines(d),
    "bpe": lambda d, lab: byte_bpe.encode_documents(d, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN),
    "lm": lambda d, lab: lm_scoring.score(lm_scoring.fit(d, lab)),
    "bytes": lambda d, lab: suffix_doubling.drop_repeated_bytes(d),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_every_row_has_a_result(docs, labels, name):
    got = OPERATORS[name](docs, labels).collect()
    assert sorted(str(r.doc_id) for r in got) == sorted(str(r[0]) for r in ROWS)
    assert OPERATORS[name](docs.limit(0), labels.limit(0)).collect() == []


def test_repeated_rows_keep_their_lines_and_lose_their_bytes(docs):
    lines = {str(r.doc_id): r.n_removed for r in line_dedup.drop_repeated_lines(docs, min_words=5).collect()}
    assert lines["5"] == 0 and lines["6"] > 0
    gone = {str(r.doc_id): r.n_removed for r in suffix_doubling.drop_repeated_bytes(docs).collect()}
    assert gone["5"] == 800 and gone["1"] == gone["6"] == 0


def test_pages(spark):
    rows = [(1, None, None), (2, "http://a/x", ""), (3, "http://a/y", "plain &amp; text"), (3, "http://a/y", "plain &amp; text"), (4, None, "<p>a<p>b<script>x"), (5, "http://a/", "<body><div class='cookie'>no</div><main><h1>T</h1>x <b>y</b>z<aside>q</aside></main>")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit(1))
    got = sorted((r.page_id, r.text, r.n_chars) for r in html_tree.extract(pages).collect())
    assert got == [(1, "", 0), (2, "", 0), (3, "plain & text", 12), (3, "plain & text", 12), (4, "a\nb", 3), (5, "T\nx yz", 6)]
    assert html_tree.extract(pages.limit(0)).count() == 0


def test_pages_keep_columns_with_the_names_used_inside(spark):
    pages = spark.createDataFrame([(i, "http://a/x", f"<p>text {i}") for i in range(3)], "page_id long, url string, html string")
    names = ["removed", "Removed_", "__removed", "__host", "host", "salt", "row"]
    got = html_tree.extract(pages.withColumns({c: F.concat(F.lit(f"{c}-"), "page_id") for c in names})).collect()
    assert sorted(r.text for r in got) == ["text 0", "text 1", "text 2"]
    assert all(r[c] == f"{c}-{r.page_id}" for r in got for c in names)


def test_mixed_rows_keep_their_columns(docs):
    got = mixing.mixed_texts(docs)
    assert got.columns == docs.columns
    kept = got.collect()
    assert kept and all(r[c] == c for r in kept for c in CLASHING) and {r.doc_id for r in kept} <= {None, 5, 6}
    assert mixing.mixed_texts(docs.limit(0)).collect() == []


def test_vectors(spark):
    rows = [(0, [1.0, 0.0]), (50, None), (100, [0.0, 0.0]), (1, [1.0, None]), (2, [float("nan"), 1.0]), (3, [2.0, 0.0]), (4, [3.0, 0.0]), (None, [1.0, 1.0]), (5, [0.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumns({"v": F.lit(1), "perm": F.lit(2)})
    ask = lambda d: permutation_index.nearest(d, lambda i: F.pmod(i, F.lit(50)) == 0, 5)
    assert sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in ask(df).collect()) == [(0, 1, 3, 1.0), (0, 2, 4, 1.0), (0, 3, 5, 0.0)]
    assert ask(df.limit(0)).count() == 0
