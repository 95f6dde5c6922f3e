from pyspark.sql import functions as F

from forestmine.functions import sql
from forestmine.operators import match
from forestmine.sources import generator, tables
from forestmine.streaming import sessions

DIR = "/root/testdata/sf0.001"


def test_stream_supports_equal_batch(spark, tmp_path):
    codes = ["session@0 view@1", "session@0 view@1 purchase@2", "session@0 click@1 click@1"]
    events = sessions.read_events(spark, DIR, "events.parquet")
    counts = sessions.watched_counts(sessions.session_trees(events), codes)
    out = str(tmp_path / "support")
    q = counts.writeStream.foreachBatch(sessions.merge_support(out)).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert q.exception() is None
    got = {r["code"]: r["support"] for r in sessions.read_support(spark, out).collect()}
    v = tables.sessions_rank(spark, DIR).persist()
    # Sessions that the watermark hasn't closed yet aren't out; so the stream's supports are at most the batch's, and near them.
    for c in codes:
        whole = match.count_per_tree(v, c).agg(F.sum("n_occ")).first()[0] or 0
        assert 0.8 * whole <= got.get(c, 0) <= whole


def test_sql_surface(spark):
    sql.register(spark)
    assert spark.sql("SELECT attach_depth(array(9, 5, 3), 4), extend_rp(array(9, 5, 3), 1, 4), is_ancestor(0, 5, 3, 3), pattern_size('a@0 b@1'), pattern_depth('a@0 b@1 c@2')").first()[:] == (1, [9, 5, 4], True, 2, 2)
    generator.literal_forest(spark, ["a(b,b)", "a(b)"]).createOrReplaceTempView("v")
    got = {tuple(r) for r in spark.sql("SELECT code, size, support FROM mine_forest(TABLE(v) WITH SINGLE PARTITION, 2, 2)").collect()}
    assert got == {("a@0", 1, 2), ("b@0", 1, 3), ("a@0 b@1", 2, 3)}


def test_stateful_sessions_are_those_of_the_window(spark, tmp_path):
    def run(make, name):
        q = make(sessions.read_events(spark, DIR, "events.parquet")).writeStream.format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination(120)
        assert q.exception() is None
        return {(r["user_id"], r["start"], tuple((n["lo"], n["hi"], n["label"]) for n in r["nodes"])) for r in spark.table(name).collect()}

    window, state = run(sessions.session_trees, "by_window"), run(sessions.session_trees_stateful, "by_state")
    assert window and state == window


def test_windowed_support(spark):
    rows = [(1, "2024-01-01 10:00:00", "a@0", 2), (2, "2024-01-02 10:00:00", "a@0", 3), (1, "2024-01-09 10:00:00", "a@0", 5)]
    counts = spark.createDataFrame(rows, "user_id long, end string, code string, n_occ long").withColumn("end", F.col("end").cast("timestamp"))
    got = sorted((r["support"], r["tree_support"]) for r in sessions.windowed_support(counts, "7 days").collect())
    # Weeks of windows begin on Thursdays: the first two rows share one, the third is in the next.
    assert got == [(5, 1), (5, 2)]
