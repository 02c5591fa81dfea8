import numpy as np

from lincompress.operators import compress as C
from lincompress.operators.fit import fit_compressed
from lincompress.plans.design import ModelSpec, num
from lincompress.plans.registry import Registry
from lincompress.plans.sqltext import compress_stats_sql
from lincompress.sources.tables import load, panel_generator, save_bucketed
from lincompress.streaming import compress_stream as cs

SF = "/root/testdata/sf0.001"
SPEC = ModelSpec("value", (num("hour"),))


def parts(spark, tmp_path, days):
    e = load(spark, SF, "events").selectExpr("event_id", "ts", "user_id", "value", "hour(ts) as hour", "day(ts) as d")
    for k in days:
        e.where(f"d % 3 = {k}").drop("d").write.mode("append").parquet(str(tmp_path / "in"))
    return e


def test_micro_batches_add_up_and_retries_do_not(spark, tmp_path):
    e = parts(spark, tmp_path, (0, 1))
    schema = e.drop("d").schema
    seen = []
    apply = cs.refresh_each_batch(str(tmp_path / "store"), SPEC, lambda cf, i: seen.append(fit_compressed(cf).coef[:, 0]))

    def drain():
        q = spark.readStream.schema(schema).parquet(str(tmp_path / "in")).writeStream.foreachBatch(apply).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
        q.awaitTermination()

    drain()
    parts(spark, tmp_path, (2,))
    drain()
    whole = fit_compressed(C.compress_stats(e, SPEC))
    assert len(seen) == 2 and np.allclose(seen[-1], whole.coef[:, 0])
    apply(e.where("d % 3 = 2").drop("d"), 1)
    assert np.allclose(seen[-1], whole.coef[:, 0])


def test_state_of_each_user(spark, tmp_path):
    old = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        e = parts(spark, tmp_path, (0, 1, 2))
        stream = spark.readStream.schema(e.drop("d").schema).parquet(str(tmp_path / "in")).selectExpr("user_id", "cast(hour as double) as x", "value as y")
        out = cs.moments_by_user(stream, "user_id", "x", "y")
        got = {r.user_id: r for r in cs.run_available(out, "moments", str(tmp_path / "cp2"), "update").collect()}
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", old)
    want = {r.user_id: r for r in e.groupBy("user_id").agg({"value": "sum", "*": "count"}).collect()}
    assert got.keys() == want.keys()
    assert all(got[u].cnt == w["count(1)"] and np.isclose(got[u].sy, w["sum(value)"]) for u, w in want.items())


def test_registry_answers_narrower_models_only(spark):
    rows = panel_generator(spark, 200, 5)
    held = Registry()
    held.add(C.compress_stats(rows, ModelSpec("y", (num("arm"), num("x1"), num("t")))))
    a = fit_compressed(held.find(ModelSpec("y", (num("arm"),)), "t < 3", ("t",)), "ehw")
    b = fit_compressed(C.uncompressed(rows.where("t < 3"), ModelSpec("y", (num("arm"),))), "ehw")
    assert np.allclose(a.coef, b.coef) and np.allclose(a.cov[0], b.cov[0])
    assert held.find(ModelSpec("y", (num("x2"),))) is None and held.find(ModelSpec("z", (num("arm"),))) is None
    assert held.find(ModelSpec("y", (num("arm"),), cluster="unit")) is None


def test_sql_text_is_the_compression(spark):
    spec = ModelSpec("y", (num("arm"), num("x1")))
    panel_generator(spark, 100, 4).createOrReplaceTempView("panel_rows")
    text = compress_stats_sql(spec, "panel_rows").replace('"', "`")
    key = lambda df: sorted((r.arm, r.x1, r.cnt, round(r.sy_y, 9)) for r in df.collect())
    assert key(spark.sql(text)) == key(C.compress_stats(spark.table("panel_rows"), spec).df)


def test_bucketed_clusters_need_no_exchange(spark):
    save_bucketed(panel_generator(spark, 300, 6), "bucketed_panel", "unit", 4)
    spec = ModelSpec("y", (num("arm"), num("t")), cluster="unit")
    cf = C.compress_cluster_moments(spark.table("bucketed_panel"), spec)
    plan = cf.df._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    raw = C.uncompressed(spark.table("bucketed_panel"), spec)
    assert np.allclose(fit_compressed(cf, "cluster").cov[0], fit_compressed(raw, "cluster").cov[0])
    spark.sql("DROP TABLE bucketed_panel")


def test_plan_reads_used_columns_and_combines_before_the_exchange(spark):
    cf = C.compress_stats(load(spark, SF, "lineitem"), ModelSpec("l_quantity", (num("l_discount"),)))
    plan = cf.df._jdf.queryExecution().executedPlan().toString()
    assert "partial_sum" in plan and "ReadSchema: struct<l_quantity:double,l_discount:double>" in plan.replace("\n", "")


def test_results_of_streams_go_to_files_not_through_the_driver(spark, tmp_path):
    e = parts(spark, tmp_path, (0, 1, 2)).drop("d")
    stream = lambda: spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    held = cs.run_available(cs.compress_stream(stream(), SPEC), "held", str(tmp_path / "cp3"))
    assert held.inputFiles() and {(r.hour, r.cnt) for r in held.collect()} == {(r.hour, r["count"]) for r in e.groupBy("hour").count().collect()}
    rows = cs.run_available(stream().select("event_id"), "rows", str(tmp_path / "cp4"), "append")
    assert len({f.rsplit("/", 2)[1] for f in rows.inputFiles()}) > 1
    assert sorted(r[0] for r in rows.collect()) == sorted(r[0] for r in e.select("event_id").collect())
    (tmp_path / "none").mkdir()
    nothing = cs.run_available(cs.compress_stream(spark.readStream.schema(e.schema).parquet(str(tmp_path / "none")), SPEC), "nothing", str(tmp_path / "cp5"))
    assert nothing.columns == held.columns and nothing.count() == 0


def test_session_and_dedup_queries_hold_no_result_on_the_driver(spark):
    from lincompress.relops import QUERIES

    sessions = QUERIES["stream_session"](spark, SF)
    assert all("stream-" in f for f in sessions.inputFiles()) and sessions.inputFiles()
    assert sessions.agg({"cnt": "sum"}).first()[0] == load(spark, SF, "events").count()
    once = QUERIES["stream_dedup"](spark, SF)
    kept = spark.read.parquet(*once.inputFiles())
    assert kept.columns == ["event_id", "ts"] and kept.count() == once.first().n == load(spark, SF, "events").select("event_id").distinct().count()
