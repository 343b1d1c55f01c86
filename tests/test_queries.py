import duckdb
import pytest

from pathloom import queries
from pathloom.sources.graphs import TABLES
from pathloom.views import VIEWS

SF = "/root/testdata/sf0.001"
#: A query of each kind; the driver compares them all.
CHOSEN = ["view_d1", "view_d4", "view_d10", "view_s6", "view_s7", "closure_doubling_transfer", "incr_d8", "delta_old_prefix_xjoin", "delta_detectable_rows", "update_diff", "measure_published_gain", "measure_published_claims", "op_asof", "op_range_join", "op_session", "op_stream_dedup"]


@pytest.mark.parametrize("name", CHOSEN)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = queries.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    want = con.sql(f"SELECT {', '.join(cols)} FROM ({queries.SQL[name]}) AS q").fetchall()
    assert sorted(map(repr, (tuple(r) for r in df.select(cols).collect()))) == sorted(map(repr, want))


def test_view_sizes(spark):
    for name, n in {"d3": 152, "d8": 13, "s10": 2}.items():
        assert queries.QUERIES[f"view_{name}"](spark, SF).count() == n
    assert set(queries.SQL) <= set(queries.QUERIES) and len(VIEWS) == 24


def test_chain_processor_links_successors(spark, tmp_path):
    from pathloom.streaming.maintenance import chain_stream

    rows = [(20, "click", 1, "2024-01-01 00:00:00"), (21, "click", 2, "2024-01-01 00:01:00"), (22, "click", 3, "2024-01-01 00:02:00")]
    df = spark.createDataFrame(rows, "event_id long, event_type string, user_id long, ts string").selectExpr("event_id", "event_type", "user_id", "CAST(ts AS timestamp) AS ts")
    df.write.parquet(str(tmp_path / "in"))
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        out = chain_stream(spark.readStream.schema(df.schema).parquet(str(tmp_path / "in")))
        out.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start().awaitTermination()
        assert [tuple(r) for r in spark.read.parquet(str(tmp_path / "out")).collect()] == [("relay_click", 11 * 10**12 + 1, 11 * 10**12 + 2)]
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")


@pytest.mark.parametrize("name", ["delta_detectable_rows", "measure_published_gain", "measure_published_claims"])
def test_query_reads_given_tables(spark, name):
    assert any("/sf0.001/" in f for f in queries.QUERIES[name](spark, SF).inputFiles())
