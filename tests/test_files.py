import pytest

from graphparts.operators.components import connected_components
from graphparts.operators.graph import graph_of
from graphparts.plans.skew import hub_limit, join_per_key
from graphparts.sources import files
from graphparts.streaming import edges as s

EDGES = [(0, 3, 2), (3, 9, 1), (2**60, 2**60 + 5, 1)]


@pytest.mark.parametrize("fmt", files.FORMATS)
def test_round_trip(spark, tmp_path, fmt):
    g = graph_of(spark.createDataFrame(EDGES, "src bigint, dst bigint, w bigint"))
    files.write_edges(g, str(tmp_path / "e"), fmt)
    want = [(a, b, 1 if fmt == "adjacency" else w) for a, b, w in EDGES]
    assert sorted(map(tuple, files.read_edges(spark, str(tmp_path / "e"), fmt).collect())) == want
    with pytest.raises(ValueError):
        files.read_edges(spark, str(tmp_path / "e"), "none")


def test_text_of_others(spark, tmp_path):
    (tmp_path / "a.txt").write_text("# a comment\n1 2\n\n  3\t4  7\n% another\n5,6\n")
    assert sorted(map(tuple, files.read_edges(spark, str(tmp_path / "a.txt"), "text").collect())) == [(1, 2, 1), (3, 4, 7), (5, 6, 1)]
    (tmp_path / "m.mtx").write_text("%%MatrixMarket matrix coordinate pattern symmetric\n% note\n5 5 2\n2 1\n5 4\n")
    assert sorted(map(tuple, files.read_edges(spark, str(tmp_path / "m.mtx"), "matrix").collect())) == [(1, 0, 1), (4, 3, 1)]


def test_parts_and_buckets(spark, tmp_path):
    parts = spark.createDataFrame([(1, 0), (2, 1), (3, 0)], "v bigint, part int")
    for fmt in ("vector", "parquet"):
        files.write_parts(parts, str(tmp_path / fmt), fmt)
        assert sorted(map(tuple, files.read_parts(spark, str(tmp_path / fmt), fmt).collect())) == [(1, 0), (2, 1), (3, 0)]
    g = graph_of(spark.createDataFrame(EDGES, "src bigint, dst bigint, w bigint"))
    try:
        arcs = files.bucketed_arcs(g, "graphparts_test_arcs", 4)
        plan = arcs.groupBy("u").count()._jdf.queryExecution().executedPlan().toString()
        assert arcs.count() == 6 and "Exchange" not in plan
    finally:
        spark.sql("DROP TABLE IF EXISTS graphparts_test_arcs")


def test_hot_keys_join_by_broadcast(spark):
    rows = spark.createDataFrame([(0, k) for k in range(3000)] + [(k, 1) for k in range(1, 50)], "a bigint, b bigint")
    values = rows.groupBy("a").count().withColumnRenamed("count", "n").selectExpr("a", "n", "a * 10 as x")
    got = join_per_key(rows, values, "a", "n", hub_limit(rows.count()))
    assert got.columns == ["a", "b", "x"] and got.count() == 3049 and got.where("x <> a * 10").count() == 0


def test_components_with_a_hub(spark):
    star = [(0, k) for k in range(1, 2500)] + [(5000, k) for k in range(2499, 4000)] + [(7000 + k, 7001 + k) for k in range(30)] + [(None, 1), (3, 3)]
    got = {r.v: r.component for r in connected_components(spark.createDataFrame(star, "src bigint, dst bigint")).collect()}
    assert all(c == (0 if v <= 5000 else 7000) for v, c in got.items()) and len(got) == 4000 + 1 + 31


def test_late_rows_are_counted(spark, tmp_path):
    schema = "user_id bigint, ts timestamp"
    day = lambda rows, name: spark.createDataFrame(rows, "user_id bigint, t string").selectExpr("user_id", "cast(t as timestamp) as ts").coalesce(1).write.mode("append").parquet(str(tmp_path / name))
    day([(1, "2024-01-02 00:30:00"), (1, "2024-01-02 05:30:00")], "e")
    stream = spark.readStream.schema(schema).parquet(str(tmp_path / "e"))
    start = lambda: s.hourly_edges(stream).writeStream.outputMode("append").format("noop").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q = start()
    q.awaitTermination()
    assert s.dropped_late(q) == 0
    day([(1, "2024-01-01 00:00:00"), (1, "2024-01-02 06:00:00")], "e")
    q = start()
    q.awaitTermination()
    assert s.dropped_late(q) == 1
