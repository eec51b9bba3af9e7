"""Driver contract: entry, and every query that has SQL against DuckDB on the smallest tables."""

import importlib
import math
import os
import shutil
import subprocess
import sys

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES.split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def rows(df: pd.DataFrame) -> list:
    def value(v):
        if v is None or v is pd.NaT or v is pd.NA or (isinstance(v, float) and math.isnan(v)):
            return ""
        return f"{float(v):.5f}" if isinstance(v, (int, float)) or hasattr(v, "dtype") else str(v)

    df = df[sorted(df.columns)]
    return sorted([tuple(value(v) for v in r) for r in df.astype(object).itertuples(index=False)])


@pytest.mark.parametrize("name", sorted(entry.oracle_sql()))
def test_against_sql(spark, sf, duck, name):
    got, want = entry.queries()[name](spark, sf).toPandas(), duck.sql(entry.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_entry(spark):
    assert entry.entry(spark).count() == 3


def test_import_without_corpus_operators(tmp_path):
    """The package and its entry points work where the corpus operators were deleted, with or without their pipeline."""
    here = os.path.dirname(os.path.abspath(entry.__file__))
    for keep in (False, True):
        copy = tmp_path / f"copy{keep}"
        shutil.copytree(here, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", "tests", *[] if keep else ["corpus_pipeline.py"]))
        code = "import __spark_entry__ as e; q = e.queries(); assert 'exact_grid_s2' in q and not any(n.startswith('op') or n == 'pipeline' for n in q)"
        subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, env=os.environ | {"PYTHONPATH": str(copy)})


def test_broken_corpus_operators_are_an_error(tmp_path):
    here = os.path.dirname(os.path.abspath(entry.__file__))
    if not os.path.exists(os.path.join(here, "fedgrid", "llm")):
        pytest.skip("no corpus operators here")
    code = "import sys; sys.modules['xxhash'] = None; import __spark_entry__"
    got = subprocess.run([sys.executable, "-c", code], cwd=here, capture_output=True, text=True, env=os.environ | {"PYTHONPATH": here})
    assert got.returncode and "xxhash" in got.stderr


ON_TABLES = """bounds_table budget_table comm_bytes_table grid_points_cross k_local_rule_table key_agreement ledger_table renyi_table
report_protocol_table sigma_table sketch_calibration_table""".split()


@pytest.mark.parametrize("name", ON_TABLES)
def test_reads_a_table(spark, name, tmp_path):
    """No rows without the given tables: where they are missing, the query fails."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        entry.queries()[name](spark, str(tmp_path)).count()


# the function of the library that each row must come through
THROUGH = {
    "noisy_lloyd_step": "operators.kmeans.noisy_lloyd", "lloyd_five_steps": "operators.kmeans.lloyd",
    "weighted_lloyd_step_grid": "operators.kmeans.lloyd", "mean_cost": "operators.kmeans.mean_cost",
    "lsh_prefix_counts": "operators.lsh_forest.prefix_table", "exact_grid_s2": "plans.pipeline.exact_weights",
    "exact_grid_s4": "plans.pipeline.exact_weights", "pair_marginals_grouping_sets": "operators.grid_frames.pair_tables",
    "project_grid_pair": "operators.weights.project", "complement_identity_check": "plans.pipeline.exact_weights",
    "independence_nonoise": "operators.weights.independence", "independence_noisy_md5": "plans.pipeline.party_histogram",
    "fm_union_max": "operators.sketch.union", "fm_min_hash_rewrite": "operators.sketch.sketch_rows",
    "partition_sketch_long": "operators.sketch.sketch_rows", "dp_sketch_floor_phantom": "operators.sketch.privatise",
    "leave_one_out_max": "operators.weights.leave_one_out", "union_sketch_grid_s2": "operators.weights.complement_unions",
    "complement_union_raw_s2": "operators.weights.complement_weights", "simplex_consistency": "operators.weights.consistent",
    "clip_scale_consistency": "operators.weights.consistent", "cluster_sizes_sketch": "operators.weights.size_estimates",
    "align_complete": "operators.views.align", "align_semi": "operators.views.align", "align_impute": "operators.views.align",
    "align_anti": "operators.views.unmatched", "align_coverage_fullouter": "operators.views.coverage",
    "refine_rounds_s3": "operators.weights.refine", "olh_reports_md5": "operators.local_dp.olh",
    "olh_support_counts": "operators.local_dp.olh_counts", "olh_weights_s2": "operators.local_dp.olh_weights",
}


@pytest.mark.parametrize("name", THROUGH)
def test_rows_come_through_the_library(spark, sf, name, monkeypatch):
    class Called(Exception):
        pass

    def stop(*_, **__):
        raise Called

    module, function = THROUGH[name].rsplit(".", 1)
    monkeypatch.setattr(importlib.import_module(f"fedgrid.{module}"), function, stop)
    with pytest.raises(Called):
        entry.queries()[name](spark, sf).count()
