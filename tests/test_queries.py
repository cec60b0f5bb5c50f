"""Every query with SQL gives DuckDB's rows; the others give rows; nothing outside the corpus package needs it."""

from __future__ import annotations

import subprocess
import sys
from pathlib import Path

import duckdb
import pandas as pd
import pytest

from progressive_text.driver_queries import ORACLES, QUERIES
from progressive_text.plans import workloads as W
from progressive_text.sources.tables import TABLES

SF = "/root/testdata/sf0.001"
ROOT = Path(__file__).resolve().parents[1]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def rows(df) -> list[str]:
    df = df[sorted(df.columns)]
    return sorted(str(tuple(None if pd.isna(x) else x for x in r)) for r in df.astype(object).itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, duck, name):
    got, want = QUERIES[name](spark, SF).toPandas(), duck.sql(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    plain = lambda lines: [x.replace(".0,", ",").replace(".0)", ")") for x in lines]
    assert plain(rows(got)) == plain(rows(want))


@pytest.mark.parametrize("name", ["op_sample_bernoulli", "scaleout_model"])
def test_rows(spark, name):
    assert QUERIES[name](spark, SF).count() > 0


def test_approximate_figures_are_close(spark):
    for r in QUERIES["op_approximate"](spark, SF).collect():
        assert abs(r.about_users - r.users) <= 0.06 * r.users + 1 and abs(r.about_median - r.median) <= 0.05 * abs(r.median) + 1


def test_filter_runs_over_clusters_end_on_the_truth(spark):
    for name, w in (("filter_loop_kmeans", W.w3), ("filter_loop_view_counts", lambda s, d: W.w5(s, d, "view_count")), ("filter_loop_turns", W.w6), ("filter_loop_balanced", W.w4)):
        last = QUERIES[name](spark, SF).where("is_final").collect()
        truth = w(spark, SF).truth.first().truth
        assert len(last) == 1 and abs(last[0].estimate - truth) < 1e-6 and abs(last[0].estimate_stratified - truth) < 1e-6, name


def test_group_runs_over_clusters_end_on_the_truth(spark):
    for name, w in (("group_loop_full", W.w7), ("group_loop_value", W.w8b)):
        last = {r.grp: r.estimate for r in QUERIES[name](spark, SF).where("is_final").collect()}
        truth = {r.grp: r.truth for r in w(spark, SF).truth.collect()}
        assert set(last) == set(truth) and all(abs(last[k] - truth[k]) < 1e-6 for k in truth), name


def test_table_function_reads_every_event(spark):
    ids = {r.event_id for r in QUERIES["op_udtf_all_fields"](spark, SF).select("event_id").distinct().collect()}
    assert ids == {r.event_id for r in spark.read.parquet(f"{SF}/events.parquet").select("event_id").collect()}


def test_entry_runs_without_the_corpus_operators(tmp_path):
    for p in ("progressive_text", "__spark_entry__.py"):
        (tmp_path / p).symlink_to(ROOT / p) if p.endswith(".py") else (tmp_path / p).mkdir()
    for p in (ROOT / "progressive_text").iterdir():
        if p.name != "llm":
            (tmp_path / "progressive_text" / p.name).symlink_to(p)
    code = "import sys; sys.path.insert(0, '.'); import __spark_entry__ as e; assert 'filter_priority' in e.queries() and not any(k == 'pipeline' for k in e.queries()) and e.oracle_sql()"
    (tmp_path / "entry.py").write_text((ROOT / "__spark_entry__.py").read_text())
    (tmp_path / "__spark_entry__.py").unlink()
    (tmp_path / "entry.py").rename(tmp_path / "__spark_entry__.py")
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, timeout=120)


def test_sliding_windows_take_seconds_as_their_sql_does(spark, duck, tmp_path):
    """The last half second before a window's start, halves that round to even, and times before 1970."""
    times = ["2024-01-08 17:59:59.49", "2024-01-08 17:59:59.5", "2024-01-08 17:59:59.7", "2024-01-08 18:00:00", "2024-01-08 17:59:58.5", "1969-12-31 23:00:00", "1969-12-31 11:59:59.6"]
    duck.sql(f"COPY (SELECT i AS event_id, t::TIMESTAMP AS ts, i % 7 AS user_id, 'click' AS event_type, i * 1.5::DOUBLE AS value, '{{}}' AS props FROM (SELECT unnest({times}) AS t, unnest(range({len(times)})) AS i)) TO '{tmp_path}/events.parquet' (FORMAT parquet)")
    got = QUERIES["op_sliding_window"](spark, str(tmp_path)).toPandas()
    want = duckdb.sql(ORACLES["op_sliding_window"].replace("FROM events)", f"FROM '{tmp_path}/events.parquet')")).df()
    assert rows(got) == rows(want) and len(want) >= 8
