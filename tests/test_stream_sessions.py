"""Sessions of the events feed are written by tasks: nothing of them is gathered in the driver."""

from docprofile import queries
from docprofile.streaming import stream as S


def test_sessions_are_no_table_in_memory(spark, sf):
    store, held = spark.conf.get(S.STATE_STORE), {t.name for t in spark.catalog.listTables()}
    got = queries.stream_sessions(spark, sf)
    want = spark.read.parquet(f"{sf}/events.parquet").groupBy("user_id").count()
    assert sorted(map(tuple, got.collect()), key=repr) == sorted(map(tuple, want.collect()), key=repr)
    assert {t.name for t in spark.catalog.listTables()} == held and "MemoryPlan" not in got._jdf.queryExecution().toString()
    assert spark.conf.get(S.STATE_STORE) == store
