import pytest
from conftest import same

from meshprofile.plans import registry

QUICK = [k for k in registry.oracle_sql() if k != "missed_patterns"]  # see test_elbow_and_missed_patterns


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_its_sql(spark, sf, duck, name):
    same(registry.queries()[name](spark, sf), duck.execute(registry.oracle_sql()[name]))


def test_sweep_reports_measured_rounds(spark, sf):
    got = registry.queries()["topology_sweep"](spark, sf).orderBy("topology").collect()
    assert len(got) == 9 and all(r.rounds > 0 and r.seconds > 0 for r in got)
    assert got[0].rounds > 3 * got[8].rounds and all(abs(r.rounds - r.predicted) <= 0.6 * r.predicted + 3 for r in got)


def test_audit_values(spark, sf):
    got = {r.audit: r.value for r in registry.queries()["privacy_audit"](spark, sf).collect()}
    assert got["rounded counts"] == 1 and got["rounded counts, scaled"] < 0.3
    assert got["rebuild error, exposed edge"] < 1e-9 and got["rebuild error, safe edge"] > 0.01
    assert got["guessed masks"] == 0 and got["shared draws"] == 0
    assert got["repeated draws, 50"] < 0.1


def test_upload_from_measured_rounds(spark, sf):
    for r in registry.queries()["upload_measured"](spark, sf).collect():
        assert r.floats == 294 and r.degree == 5 and r.bytes == 4 * 294 * 5 * r.rounds and 25 <= r.rounds / r.iterations <= 35
        assert abs(r.seconds - r.bytes * 8 / r.mbit_s / 1e6) < 1e-9


@pytest.mark.parametrize("name", ["sample_hash", "sample_bernoulli", "sample_stratified"])
def test_samples(spark, sf, name):
    got = registry.queries()[name](spark, sf)
    ids = [r.event_id for r in got.collect()]
    share = {"sample_hash": 0.1, "sample_bernoulli": 0.1, "sample_stratified": 0.12}[name]
    assert len(set(ids)) == len(ids) and abs(len(ids) / 10_000 - share) < 0.05


def test_full_covariance_queries_agree(spark, sf):
    a, b = ({(r.k, r.slot): r for r in registry.queries()[f"gmm_full_{kind}"](spark, sf).collect()} for kind in ("central", "masked"))
    assert len(a) == 36 and all(abs(a[i].mu - b[i].mu) <= 1e-3 and abs(a[i].log_likelihood - b[i].log_likelihood) < 1 for i in a)


def test_plans_prune_and_push(spark, sf):
    plan = registry.queries()["scan_filtered"](spark, sf)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(" in plan and "props" not in plan.split("ReadSchema")[1]


def test_entry(spark):
    assert registry.entry(spark).columns == ["k", "size", "mu"]


def test_message_sink_refuses_private_columns(spark, tmp_path):
    from meshprofile.sources.io import message_sink

    with pytest.raises(ValueError):
        message_sink(spark.createDataFrame([(1, 2.0)], "t int, state double"), str(tmp_path / "m"))


def test_schema_check(spark):
    from meshprofile.session import STATE, require_schema

    with pytest.raises(ValueError):
        require_schema(spark.createDataFrame([(1, 2.0)], "party int, x double"), STATE)


def test_late_stream_takes_rows_of_any_date(spark):
    from meshprofile.streaming.streams import thirds

    e = spark.sql("select * from values (1, timestamp_ntz '2019-05-01'), (2, timestamp_ntz '2024-01-15'), (3, timestamp_ntz '2031-01-01'), (4, null) as v(event_id, ts)")
    assert sorted(r.event_id for part in thirds(e) for r in part.collect()) == [1, 2, 3, 4]
    assert thirds(e)[1].count() + thirds(e)[2].count() == 2


def test_family_times_on_both_carriers(spark, sf):
    got = {(r.carrier, r.family, r.kind): r for r in registry.queries()["family_times"](spark, sf).collect()}
    assert len(got) == 12
    for (carrier, family, kind), r in got.items():
        assert r.converged and r.iterations == got[carrier, family, "central"].iterations
        assert kind == "central" or r.local_seconds < got[carrier, family, "central"].local_seconds


def test_a_cluster_without_a_shared_folder_is_refused():
    from types import SimpleNamespace

    from meshprofile import session

    none = SimpleNamespace(getOrElse=lambda _: None)
    context = SimpleNamespace(master="spark://host:7077", _jsc=SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: none)))
    fake = SimpleNamespace(sparkContext=context, conf=SimpleNamespace(get=lambda *_: None))
    with pytest.raises(RuntimeError):
        session.shared_folder(fake)


def test_extreme_values_that_tie_name_the_first_event(spark, tmp_path):
    rows = [(i, f"2024-01-0{1 + i % 3} 0{i % 7}:00:00", i % 4, "click", v) for i, v in enumerate([5.0, 1.0, 9.0, 1.0, 9.0, None, 1.0, 9.0])]
    e = spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double")
    e.withColumn("ts", e.ts.cast("timestamp_ntz")).selectExpr("*", "'' as props").repartition(4).write.parquet(str(tmp_path / "events.parquet"))
    got = registry.queries()["agg_stats"](spark, str(tmp_path)).first()
    assert (got.top, got.low) == (2, 1)


def test_slots_rank_by_sums_added_in_the_order_of_ids(spark, tmp_path):
    """0.1 + 0.2 + 0.3 is more than 0.6 only from left to right; a null sum ranks last."""
    import duckdb

    def rows(start, *values):
        return [(start + i, f"2024-01-01 {h:02}:00:00", 1, v) for i, (h, v) in enumerate(values)]

    parts = [rows(0, (5, 0.1), (1, 2.0), (2, 1.0), (7, None)), rows(4, (5, 0.2), (5, 0.3), (3, 0.6))]
    for i, part in enumerate(parts):
        e = spark.createDataFrame(part, "event_id long, ts string, user_id long, value double").coalesce(1)
        e = e.selectExpr("event_id", "cast(ts as timestamp_ntz) as ts", "user_id", "'click' as event_type", "value", "'' as props")
        e.sortWithinPartitions("event_id").write.mode("append").parquet(str(tmp_path / "events.parquet" / f"part={i}"))
    c = duckdb.connect(config={"threads": 1})
    c.execute(f"create view events as select * from read_parquet('{tmp_path}/events.parquet/*/*.parquet', hive_partitioning = false)")
    got = registry.queries()["join_lateral"](spark, str(tmp_path))
    assert sorted(r.slot for r in got.collect()) == [2, 4, 10]
    same(got, c.execute(registry.oracle_sql()["join_lateral"]))


def test_null_sums_rank_after_others(spark, tmp_path):
    e = spark.createDataFrame([(i, f"2024-01-01 {i:02}:00:00", 1, v) for i, v in enumerate([None, 1.0, 2.0, 3.0])], "event_id long, ts string, user_id long, value double")
    e.selectExpr("event_id", "cast(ts as timestamp_ntz) as ts", "user_id", "'click' as event_type", "value", "'' as props").write.parquet(str(tmp_path / "events.parquet"))
    assert sorted(r.slot for r in registry.queries()["join_lateral"](spark, str(tmp_path)).collect()) == [2, 4, 6]
