"""Near-copy dedup on shingle sets against brute force."""

import random
from collections import defaultdict

import corpus_pipeline as P
from docprofile.llm import near

SF = "/root/testdata/sf0.01"


def brute_near(rows, size=5):
    """Indices of the rows that stay."""
    sets = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        sets.append({b" ".join(w[k : k + size]) for k in range(max(1, len(w) - size + 1))})
    comp, by = list(range(len(rows))), defaultdict(list)
    for k, s in enumerate(sets):
        for x in s:
            by[x].append(k)

    def root(x):
        while comp[x] != x:
            x = comp[x]
        return x

    for a, b in {(a, b) for ks in by.values() for a in ks for b in ks if a < b}:
        if 9 * len(sets[a] & sets[b]) >= 4 * (len(sets[a]) + len(sets[b])):
            comp[root(a)] = root(b)
    groups = defaultdict(list)
    for k, (i, _) in enumerate(rows):
        groups[root(k)].append((i is None, i or 0, k))
    return sorted(min(g)[2] for g in groups.values())


def test_pipeline_catches_similar_texts(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    want = {rows[k][0] for k in brute_near(rows)}
    got = P.near_stage(spark, docs, SF)
    assert got.columns == docs.columns
    assert {r.doc_id for r in got.collect()} == want and got.count() == len(want)


def test_crowded_keys(spark):
    rng = random.Random(5)
    base, line = [f"w{k}" for k in range(60)], [f"common{k}" for k in range(25)]
    rows = []
    for i in range(90):
        w = list(base)
        for _ in range(rng.randrange(4)):
            w[rng.randrange(60)] = f"x{rng.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    rows += [(100 + i, " ".join(line + [f"y{i}_{k}" for k in range(rng.choice((2, 6, 40)))])) for i in range(90)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = [rows[k][0] for k in brute_near(rows)]
    for crowd, rounds in ((1, 0), (5, 2)):
        assert sorted(r.doc_id for r in near.keep_one(df, crowd=crowd, rounds=rounds).collect()) == want
    assert near.keep_one(df.limit(0)).count() == 0
