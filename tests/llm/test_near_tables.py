"""What the near stage writes and shuffles of sets: only those that are asked for, and no table stays that isn't needed."""

import os
import re

import numpy as np

from docprofile.llm import common, near


def test_stage_leaves_no_sets(spark, tmp_path, monkeypatch):
    base, rows = [f"w{k}" for k in range(60)], []
    for i in range(40):
        w = list(base)
        w[i % 60] = f"x{i}"
        rows.append((i, " ".join(w)))
    rows += [(100 + i, " ".join(f"y{i}_{k}" for k in range(60))) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    crowd, held, tell = [], [], near.materialise

    def kept(table, tag):
        out = tell(table, tag)
        if tag in ("held", "crowd"):
            (held if tag == "held" else crowd).append(out.count())
        return out

    monkeypatch.setattr(near, "materialise", kept)
    monkeypatch.setattr(common, "shared_folder", lambda spark: str(tmp_path))
    got = near.keep_one(df, crowd=8, rounds=0)
    tags = {re.sub("-[0-9a-f]{32}$", "", t) for t in os.listdir(tmp_path)}
    assert {"sets", "prefixes", "held", "asked", "shared", "crowd", "apart", "subs"}.isdisjoint(tags) and "kept" in tags
    assert crowd and held and max(held) <= 40
    assert sorted(r.doc_id for r in got.collect()) == [0, *range(100, 160)]


def test_marks_pass_every_key(spark):
    rng = np.random.default_rng(1)
    keys, others = (rng.integers(-(2**63), 2**63 - 1, n, dtype=np.int64) for n in (5000, 100_000))
    df = spark.createDataFrame([(int(k),) for k in keys], "key long")
    met = near.marked(*near.marks(df, len(keys)))
    assert met(keys).all() and met(others).mean() < 0.1
    none = near.marked(*near.marks(df.limit(0), 0))
    assert not none(keys).any()


def test_discarded_tables_are_gone(spark):
    t = common.materialise(spark.range(10), "t")
    assert t.count() == 10
    common.discard(t)
    assert not os.path.exists(t.written.removeprefix("file://"))
