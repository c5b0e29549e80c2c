"""Rows that repeat an id or have none: each is a document of its own."""

from graphsieve.llm import near_copies, simhash

ROWS = [(None, "the first text of its kind"), (None, "a second one that differs wholly"), (None, "the first text of its kind"), (7, "seven in a row went home"), (7, "other words under an old number"), (3, "the first text of its kind"), (8, "a second one that differs wholly")]
WANT = sorted([(3, ROWS[0][1]), (7, ROWS[3][1]), (7, ROWS[4][1]), (8, ROWS[1][1])])


def test_null_and_repeated_ids(spark):
    docs = spark.createDataFrame([*ROWS, (None, "alone without a number here")], "doc_id long, text string")
    for keep in (simhash.keep_one, near_copies.keep_one_similar):
        got = [tuple(r) for r in keep(docs).collect()]
        assert sorted(r for r in got if r[0] is not None) == WANT
        assert [r for r in got if r[0] is None] == [(None, "alone without a number here")]
