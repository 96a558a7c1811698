"""Every query that has SQL, against that SQL in another engine, on the smallest tables; plans and claims."""

import os

import duckdb
import pandas as pd
import pytest

from elastipool.plans.full import CATALOG

SAMPLE = [
    "ingest_quality", "text_stats_by_lang_source", "sample_balanced_lang", "sample_proportional_quality", "train_split_quality", "leakage_lang", "leak_benchmark", "tasks_lang", "arrivals_grid", "events_warp",
    "sequential_lindley", "fifo_two_fold", "fifo_equal_residue", "priority_static_two", "busy_at_polls", "fluid_events_elastic", "rule_truth_table", "rule_bounds", "op_sql_function_rule", "replay_events", "elastic_results",
    "elastic_polls", "elastic_snapshots", "elastic_experience", "zs_fast_lang", "zs_shape_quality", "nb_lang", "faulty_results", "guarded_external", "accuracy_matrix", "precision_f1", "five_lang_queue", "five_lang_seconds", "five_quality_report", "five_lang_tasks",
    "five_quality_scores", "prediction_invariance", "fault_trace", "elastic_drain_results", "elastic_spinup_polls", "provision_warped", "experience_sweep", "stream_late_count", "stream_waves", "op_tsv_roundtrip", "shards_orders_sequential", "stream_processor_results", "stream_session_users",
]


def _norm(d: pd.DataFrame) -> list[tuple]:
    def one(v):
        if v is None or v is pd.NaT or (isinstance(v, float) and v != v) or v is pd.NA:
            return "NULL"
        return repr(round(float(v), 6)) if isinstance(v, float) else str(v)

    return sorted(tuple(one(v) for v in r) for r in d[sorted(d.columns)].astype(object).itertuples(index=False))


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{sf}/{f}'")
    return c


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, sf, con, name):
    f, sql = CATALOG[name]
    got, want = f(spark, sf).toPandas(), con.execute(sql).fetchdf()
    assert sorted(got.columns) == sorted(want.columns)
    assert len(got) == len(want)
    for a, b in zip(_norm(got), _norm(want)):
        assert all(x == y or (x.replace(".0", "") == y.replace(".0", "")) for x, y in zip(a, b)), (a, b)


def test_scheduler_plan_reads_no_text(spark, sf):
    from elastipool.operators import sampling, workload
    from elastipool.sources import ingest

    lang = ingest.table(spark, sf, "documents").select("doc_id", "lang", "n_chars", "source")
    plan = workload.service("zs_fast")
    text = lang.withColumn("svc_ms", plan)._jdf.queryExecution().executedPlan().toString()
    assert "text" not in text.split("ReadSchema")[1]
    assert sampling.key() is not None


def test_fast_classifier_stays_in_codegen(spark, sf):
    plan = CATALOG["zs_fast_lang"][0](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Exchange" not in plan


def test_elastic_beats_static_and_sequential(spark, sf):
    r = {x.run_id: x for x in CATALOG["queue_summary"][0](spark, sf).collect()}
    assert r["B1"].peak <= r["B3"].peak <= r["B4"].peak + 5
    assert r["B1"].drain_ms <= r["B3"].drain_ms


def test_tsv_and_requests(spark, sf, tmp_path):
    from elastipool.sources import ingest

    p = tmp_path / "x.tsv"
    p.write_text("spam\twin now\nham\thello\nno tab here\n\nham\t\n")
    rows = ingest.tsv(spark, str(p)).collect()
    assert [(r.y, r.text) for r in rows][:2] == [("spam", "win now"), ("ham", "hello")]
    assert [r.bad for r in rows if r.bad] == ["no tab here"]
    assert ingest.conversations(spark, sf).count() > 0


READS = {"arrivals_grid": "supplier", "op_sql_function_rule": "lineitem", "rule_bounds": "lineitem", "rule_truth_table": "lineitem", "source_two_phase": "customer", "stream_two_phase": "customer"}


@pytest.mark.parametrize("name", READS)
def test_query_reads_its_table(spark, sf, con, tmp_path, name):
    """The result follows the given table: half of its rows give what the SQL gives for them."""
    f, sql = CATALOG[name]
    table = READS[name]
    spark.read.parquet(f"{sf}/{table}.parquet").where(f"{spark.read.parquet(f'{sf}/{table}.parquet').columns[0]} % 2 = 1").write.parquet(str(tmp_path / f"{table}.parquet"))
    half = duckdb.connect()
    half.execute(f"CREATE VIEW {table} AS SELECT * FROM '{tmp_path}/{table}.parquet/*.parquet'")
    got, want, whole = (_norm(x) for x in (f(spark, str(tmp_path)).toPandas(), half.execute(sql).fetchdf(), con.execute(sql).fetchdf()))
    assert [[x.replace(".0", "") for x in r] for r in got] == [[x.replace(".0", "") for x in r] for r in want]
    assert got and want != whole


@pytest.mark.parametrize("name", READS)
def test_query_on_an_empty_table(spark, sf, tmp_path, name):
    spark.read.parquet(f"{sf}/{READS[name]}.parquet").where("false").write.parquet(str(tmp_path / f"{READS[name]}.parquet"))
    assert CATALOG[name][0](spark, str(tmp_path)).collect() == []
