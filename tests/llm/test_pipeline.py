"""The pipeline against a brute-force version, stage by stage, and on odd rows."""

import re
from collections import defaultdict

import corpus_pipeline as P
from docprofile.llm import pii, quality, secrets
from docprofile.llm.queries import quality_scorer
from tests.llm.test_operators import ODD, brute_secrets, brute_simhash, check_packing, texts

SF = "/root/testdata/sf0.01"


def brute_exact(rows):
    groups = defaultdict(list)
    for i, t in rows:
        groups[re.sub(r"[\x20\x09-\x0D]", "", t or "")].append((-len(t or ""), i))
    return {min(g)[1] for g in groups.values()}


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    scorer = quality_scorer(spark, docs, SF)
    assert [n for n, _ in P.STAGES][2] == "simhash near-dedup" and len(P.STAGES) == 5
    kept = []
    for k, (_, stage) in enumerate(P.STAGES):
        before = texts(docs)
        stage(spark, docs, SF).write.parquet(str(tmp_path / str(k)))
        columns, docs = docs.columns, spark.read.parquet(str(tmp_path / str(k)))
        if k < 4:
            assert docs.columns == columns
            kept.append(docs.count())
        if k == 0:
            assert {i for i, _ in texts(docs)} == {i for i, t in before if scorer.score((t or "").encode()) >= 0.5}
        elif k == 1:
            assert {i for i, _ in texts(docs)} == brute_exact(before)
        elif k == 2:
            assert {i for i, _ in texts(docs)} == {c for _, _, c in brute_simhash(before)}
        elif k == 3:
            was = dict(before)
            assert set(was) == {i for i, _ in texts(docs)}
            for i, t in texts(docs):
                assert (t == was[i]) or "[SECRET]" in t
                if not brute_secrets(was[i]):
                    assert t == was[i]
            assert all(r.n_chars == len(r.text) for r in docs.where("text like '%[SECRET]%'").collect())
        else:
            n, least = check_packing(docs.collect(), before)
            assert n <= least * 1.01 + 1
    assert kept[0] >= kept[1] >= kept[2] == kept[3] > 0


def test_run_equals_stages(spark):
    got = P.run(spark, "/root/testdata/sf0.001")
    assert got.count() > 100 and {"doc_id", "piece", "sequence_id", "offset"} <= set(got.columns)


def test_odd_rows_and_empty_tables(spark):
    rows = [(i, t, "en", f"src{k % 3}", len(t or "")) for k, (i, t) in enumerate(ODD)] + [(14, "password=abcdefghijklmnop", None, None, None)]
    odd = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    s = quality.Scorer(b"good words here " * 100, b"@@@@ %%%% " * 100)
    for df in (odd, odd.limit(0)):
        out = quality.keep_good(df, s, least=0.0)
        for _, stage in P.STAGES[1:4]:
            out = stage(spark, out, SF)
            assert out.columns == odd.columns
        packed = P.packing_stage(spark, out, SF)
        assert {r.doc_id for r in packed.collect()} == {r.doc_id for r in out.collect()}
    ids = [r.doc_id for r in out.collect()]
    assert ids == []
    assert secrets.redact(odd).where("doc_id = 14").first().text == "[SECRET]"
    assert pii.replace(odd, b"k").count() == len(rows)
