import os
import shutil

from pyspark.sql import functions as F

from canopy.forest.encode import from_patterns
from canopy.functions.labels import array_children, date_label, map_children, quantile_edges, quantile_label
from canopy.pattern.codec import forest
from canopy.sql.register import match, register
from canopy.stream import sessions
from tests.conftest import SF


def events(spark):
    return spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def drain(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def test_streamed_windows_match_the_batch(spark, tmp_path):
    e = events(spark)
    e.repartitionByRange(3, "ts").write.parquet(str(tmp_path / "in"))
    q = drain(sessions.windowed(sessions.read(spark, str(tmp_path / "in"), 10), "1 day"), "w", "complete")
    got, want = spark.table("w").drop("value"), sessions.windowed(e, "1 day").drop("value")
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty() and sessions.rows_dropped(q) == 0


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    e, folder = events(spark).orderBy("ts"), tmp_path / "late"
    last = e.agg(F.max("ts")).first()[0]
    e.limit(5).coalesce(1).write.parquet(str(folder / "b"))
    e.where(F.col("ts") == last).coalesce(1).write.parquet(str(folder / "a"))
    # lateness is judged by the watermark of the batch before, so the late file comes third
    (tmp_path / "in2").mkdir()
    for k, part in enumerate("aab"):
        file = tmp_path / "in2" / f"{k}.parquet"
        shutil.copy(next((folder / part).glob("*.parquet")), file)
        os.utime(file, (1_700_000_000 + k * 100,) * 2)
    q = drain(sessions.windowed(sessions.read(spark, str(tmp_path / "in2")), "1 hour"), "late", "update")
    assert sessions.rows_dropped(q) > 0


def test_sessions_and_running_counts(spark, tmp_path):
    e = events(spark)
    found = sessions.sessions(e, "12 hours")
    assert found.agg(F.sum("n")).first()[0] == e.count()
    pairs = sessions.session_pairs(found).groupBy("anc_label", "desc_label").agg(F.sum("support").alias("support"))
    want = {(r[0], r[1]): r[2] for r in pairs.collect()}
    assert want["visit", ""] == found.count()
    sessions.session_pairs(found).coalesce(1).write.parquet(str(tmp_path / "pairs"))
    stream = spark.readStream.schema("anc_label string, desc_label string, support long").parquet(str(tmp_path / "pairs"))
    drain(sessions.running_pairs(stream), "running", "update")
    got = {(r[0], r[1]): r[2] for r in spark.table("running").groupBy("anc_label", "desc_label").agg(F.max("support")).collect()}
    assert got == want


def test_session_tree():
    assert sessions.tree_of(["view", "click", "view", "purchase", "odd"]) == [(-1, "visit"), (0, "view"), (1, "click"), (0, "view"), (3, "purchase"), (4, "odd")]
    counts = sessions.pair_counts(["view", "click", "view"])
    assert counts["view", ""] == 2 and counts["visit", "view"] == 1 and counts["view", "click"] == 1


def test_mining_micro_batches(spark, tmp_path):
    steps = "array<struct<event_type:string>>"
    rows = [([("view",), ("click",)],), ([("view",), ("click",)],)]
    spark.createDataFrame(rows, f"steps {steps}").coalesce(1).write.parquet(str(tmp_path / "s"))
    out = []
    q = sessions.mine_batches(spark.readStream.schema(f"steps {steps}").parquet(str(tmp_path / "s")), 2, lambda df, epoch: out.extend(r["code"] for r in df.where("is_maximal").collect()), str(tmp_path / "ck"))
    q.awaitTermination()
    assert out == ["visit(view(click))"]


def test_sql_functions(spark):
    register(spark)
    assert spark.sql("SELECT p_code('A(C,B)') c, p_embeds('A(B)', 'A(X(B))') e").first() == ("A(B,C)", True)
    assert spark.sql("SELECT count(*) FROM subpatterns('A(B,C)')").first()[0] == 6
    assert spark.sql("SELECT code FROM expand_class('A(B);A(C)') WHERE kind = 'cousin' AND left_code = 'A(B)'").count() == 2
    from_patterns(spark, forest("A(B); A(C)")).createOrReplaceTempView("nodes_view")
    assert match(spark, "nodes_view", "A(B)").count() == 1


def test_labels(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0], {"k": "v"}), (2, [], {})], "id long, xs array<double>, m map<string,string>")
    assert [r["label"] for r in array_children(df, "id", "xs", "x").collect()] == ["x=1.0", "x=2.0"]
    assert [r["label"] for r in map_children(df, "id", "m").collect()] == ["k=v"]
    n = spark.range(100)
    edges = quantile_edges(n, "id", 4)
    assert n.select(quantile_label("id", edges, "q").alias("q")).distinct().count() == 4
    assert events(spark).select(date_label("ts", "month").alias("m")).distinct().count() >= 1
