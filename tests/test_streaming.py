from pyspark.sql import functions as F

from graphparts.functions import udx
from graphparts.operators.graph import graph_of
from graphparts.streaming import edges as s

SF = "/root/testdata/sf0.001"


def test_replay_equals_batch(spark):
    got = {(r.user_id, r.hour): r.events for r in s.drained(s.hourly_edges(s.event_stream(spark, SF)), "hours").collect()}
    rows = spark.read.parquet(f"{SF}/events.parquet").groupBy("user_id", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("hour")).count().collect()
    assert got == {(r.user_id, r.hour): r["count"] for r in rows}


def test_running_cut_and_online_assignment(spark, tmp_path):
    rows = [(a, b) for a in range(12) for b in range(a + 1, min(a + 3, 12))]
    spark.createDataFrame(rows, "src bigint, dst bigint").write.parquet(str(tmp_path / "e"))
    stream = spark.readStream.schema("src bigint, dst bigint").parquet(str(tmp_path / "e"))
    parts = spark.createDataFrame([(v, v // 6) for v in range(12)], "v bigint, part int")
    cut = {(r.a, r.b): r.edges for r in s.drained(s.running_cut(stream, parts), "cut").collect()}
    assert cut[(0, 1)] == 3 and sum(cut.values()) == len(rows)
    both = stream.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u")))).alias("x")).select(F.lit(0).alias("bucket"), "x.v", "x.u")
    got = s.drained(s.assign_online(both, 2, 7), "online", "append").collect()
    assert sorted(r.v for r in got) == list(range(12))
    assert max(sum(r.part == k for r in got) for k in (0, 1)) <= 7


def test_functions_in_sql(spark):
    g = graph_of(spark.createDataFrame([(1, 2), (2, 3)], "src bigint, dst bigint"))
    udx.register(spark, g, spark.createDataFrame([(1, 0), (2, 0), (3, 1)], "v bigint, part int"))
    assert spark.sql("SELECT count(*) FROM gp_arcs").first()[0] == 4
    assert [tuple(r) for r in spark.sql("SELECT * FROM grid_cells(3, 2)").collect()] == [(0, 0, 0), (1, 1, 0), (2, 0, 1)]
    assert spark.sql("SELECT gini(n) FROM (SELECT part, count(*) AS n FROM gp_parts GROUP BY part)").first()[0] > 0
