"""Near copies of one text that are too far apart, held against brute force: they leave crowded keys, so few keys are made."""

import random

from docprofile.llm import near
from tests.llm.test_near import brute_near


def test_far_copies_make_few_keys(spark, monkeypatch):
    """Far copies of one text, which only a large group's core has in common, make few keys; the components stay."""
    rng = random.Random(11)
    base, rows = [f"w{k}" for k in range(150)], []
    for i in range(160):
        w = list(base)
        for k in rng.sample(range(150), rng.choice((0, 1, 2, 3, 4, 5, 6, 9, 14))):
            w[k] = f"x{rng.randrange(10**9)}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want, subs, tell = [rows[k][0] for k in brute_near(rows)], [], near.materialise

    def kept(table, tag):
        out = tell(table, tag)
        if tag == "subs":
            subs.append(out.count())
        return out

    monkeypatch.setattr(near, "materialise", kept)
    got = sorted(r.doc_id for r in near.keep_one(df, crowd=8, rounds=0).collect())
    assert got == want and 20 < len(want) < 140
    assert sum(subs) < 2000, subs
