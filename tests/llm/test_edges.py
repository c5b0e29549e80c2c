"""Nulls, empty and repeated rows, empty tables and extra columns."""

import pytest
from graphsieve.llm import decontaminate, html_text, merkle, packing, pii, quality, simhash, token_counts, token_output
from graphsieve.llm.common import tokenizer_path

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score string, items string, fp string"
ROWS = [(1, None), (2, ""), (3, "a b c d e"), (3, "a b c d e"), (None, "x y"), (4, "mail bob@example.com and +1 (212) 555-0100 now"), (5, "word " * 3000)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(d, t, "en", "s", 0, "z", "z", "z") for d, t in ROWS], DOCS)


@pytest.fixture(scope="module")
def operators(spark):
    bench = spark.createDataFrame([(1, "a b c"), (2, None), (None, "word word")], "item_id long, text string")
    labels = spark.createDataFrame([(3, 1, 0), (4, 0, 0), (None, 1, 0), (5, None, None)], "doc_id long, quality int, toxic int")
    byte, word = tokenizer_path("byte_bpe_50k.json"), tokenizer_path("word_bpe_49k.json")
    return {
        "pii": pii.pii_report, "redact": pii.redact, "tokens": lambda d: token_output.token_output(d, byte), "counts": lambda d: token_counts.token_counts(d, byte), "packing": lambda d: packing.pack_documents(d, word),
        "simhash": simhash.near_duplicates, "keep": simhash.keep_one, "merkle": merkle.edit_report, "contamination": lambda d: decontaminate.contamination_report(d, bench), "quality": lambda d: quality.quality_scores(d, labels),
    }


NAMES = ["pii", "redact", "tokens", "counts", "packing", "simhash", "keep", "merkle", "contamination", "quality"]


@pytest.mark.parametrize("name", NAMES)
def test_odd_rows(docs, operators, name):
    rows = operators[name](docs).collect()
    if name in ("pii", "redact", "tokens", "simhash", "merkle", "contamination", "quality"):
        assert len(rows) == len(ROWS)
    if name == "redact":
        assert {r.doc_id: r.text for r in rows}[4] == "mail <EMAIL> and <PHONE> now"
    if name == "contamination":
        assert {r.doc_id: r.n_hit for r in rows} == {1: 0, 2: 0, 3: 3, None: 0, 4: 0, 5: 3000}
    if name == "keep":
        assert sorted(r.doc_id for r in rows if r.doc_id is not None) == [1, 3, 4, 5]


@pytest.mark.parametrize("name", NAMES)
def test_empty_table(docs, operators, name):
    assert operators[name](docs.limit(0)).collect() == []


def test_html():
    table = "<table><tr><th>a<th>long head<tr><td>x<td>y</table>"
    assert html_text.render(table) == "a  long head\nx  y"
    assert html_text.render("<p>one<p>two<ul><li>a<li>b</ul><script>no</script><div hidden>no</div>end") == "one\n\ntwo\n\n- a\n- b\n\nend"
    assert html_text.render("<ol start=3><li>x<li>y</ol><pre>a  b\n c</pre>") == "3. x\n4. y\n\na  b\n c"
    assert html_text.render(None) == html_text.render("") == ""
    assert html_text.render("<div>" * 5000 + "deep") == "deep"
    assert html_text.render("<p>a <math><mi>x</mi></math> <svg><defs><text>no</text></defs><text>lab</text></svg> b</p>") == "a x lab b"
    assert html_text.render("<table><tr><td>" * 300 + "in" + "</table>" * 300) == "in"
    assert html_text.render("<table><tr><td colspan=400>wide<td>x<tr><td>a<td>b</table>") == "wide  x\na  b"


def test_pages(spark):
    """Null and empty pages, repeated rows, a text column that clashes, and an empty table."""
    rows = [(1, "u", None, "z"), (2, None, "", "z"), (3, "u", "<p>x", "z"), (3, "u", "<p>x", "z"), (None, "u", "word " * 1_000_000, "z")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text string")
    got = sorted((r.page_id or 0, r.n_chars) for r in html_text.extraction_report(pages).collect())
    assert got == [(0, 4_999_999), (1, 0), (2, 0), (3, 1), (3, 1)]
    assert html_text.extraction_report(pages.limit(0)).collect() == []


def test_pipeline_odd_rows(spark, tmp_path):
    """Every stage on nulls, empty and very long texts, repeated rows and clashing columns, and on an empty table."""
    import corpus_pipeline

    docs = spark.createDataFrame([(d, t, "en", "s", 0, "z", "z", "z") for d, t in [*ROWS, (6, "word " * 200_000)]], DOCS)
    for name, rows in (("some", docs), ("none", docs.limit(0))):
        folder = f"file://{tmp_path}/{name}"
        spark.createDataFrame([(3, 1, 0), (None, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
        spark.createDataFrame([(1, "p q r"), (2, None)], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
        rows.write.parquet(f"{folder}/documents.parquet")
        now = spark.read.parquet(f"{folder}/documents.parquet")
        for stage, f in corpus_pipeline.STAGES:
            out = f(spark, now, folder)
            assert stage == "packing" or out.columns == now.columns, stage
            assert bool(out.count()) == (name == "some" and stage != "quality"), stage  # with good labels alone, none scores 0.7
