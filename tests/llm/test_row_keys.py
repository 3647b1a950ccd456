"""Rows are told by id and text, so ids that are null or repeat lose no row."""

import re

import corpus_pipeline as P
from tests.llm.test_near import SF, brute_near


def test_rows_are_told_by_id_and_text(spark):
    a, b, c = ("a quick brown fox jumps over dogs " * 3, "password=abcdefghijklmnop stands in here alone", "nothing else is like this text of mine and token=qrstuvwxyzabcdef ends it")
    rows = [(None, a), (None, b), (None, c), (None, c), (7, a), (8, b + " x"), (8, "unlike all others"), (8, c.upper() + " 2")]
    df = spark.createDataFrame([(i, t, "en", f"s{k}", len(t)) for k, (i, t) in enumerate(rows)], "doc_id long, text string, lang string, source string, n_chars long")
    kept = P.near_stage(spark, df, SF)
    want = sorted((rows[k] for k in brute_near(rows)), key=repr)
    assert sorted(((r.doc_id, r.text) for r in kept.collect()), key=repr) == want and len(want) > 4
    got = sorted(((r.doc_id, r.text) for r in P.secret_stage(spark, df, SF).collect()), key=repr)
    mark = lambda t: re.sub("(?i)(password|token)=[a-z]+", "[SECRET]", t)
    assert got == sorted(((i, mark(t)) for i, t in rows), key=repr)
