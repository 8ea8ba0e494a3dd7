"""Every query that has SQL gives what the SQL gives in DuckDB."""

import pytest
from oracle_check import compare

from hushgrad import catalogue


@pytest.mark.parametrize("name", sorted(catalogue.ORACLE_SQL))
def test_equals_sql(spark, sf_dir, name):
    assert compare(spark, sf_dir, catalogue.QUERIES[name], catalogue.ORACLE_SQL[name]) == ""


def test_plans(spark, sf_dir):
    """Filters reach the scan and columns are pruned."""
    plan = catalogue.QUERIES["scan_samples"](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "GreaterThanOrEqual(l_quantity" in plan
    schema = plan.split("ReadSchema:")[1].split("\n")[0]
    assert "l_comment" not in schema and "l_tax" not in schema


READS = [
    "compressor_error",
    "cost_table",
    "gradient_cost_table",
    "m_dependence",
    "noise_draws",
    "noise_variance_table",
    "preset_table",
    "privacy_spent",
    "shift_step_table",
    "svrg_refresh",
]


@pytest.mark.parametrize("name", READS)
def test_reads_a_given_table(spark, sf_dir, name):
    """Spark reads a given table for it, and nothing is made up in its place."""
    _, physical = plan_of(catalogue.QUERIES[name](spark, sf_dir))
    assert "FileScan parquet" in physical and f"{sf_dir}/" in physical and "Range (" not in physical


def plan_of(df):
    return df._jdf.queryExecution().optimizedPlan().toString(), df._jdf.queryExecution().executedPlan().toString()


def test_noise_is_added_below_the_mask(spark, sf_dir):
    """The rows that the mask ranks and keeps already carry the noise, in plain, shifted and reduced rounds."""
    for name, windows in (("randk_message", 1), ("shifted_round", 1), ("quantized_message", 0)):
        logical, _ = plan_of(catalogue.QUERIES[name](spark, sf_dir))
        top_down = logical.split("\n")
        noise = min(i for i, x in enumerate(top_down) if "angle|noise" in x or "angle, noise" in x or "noise" in x)
        if windows:
            mask = min(i for i, x in enumerate(top_down) if "Window" in x)
            assert mask < noise, logical
        else:
            steps = min(i for i, x in enumerate(top_down) if "level" in x)
            assert steps <= noise, logical


def test_batches_keep_b_rows_before_the_shuffle(spark, sf_dir):
    _, physical = plan_of(catalogue.QUERIES["minibatch_pick"](spark, sf_dir))
    assert physical.count("WindowGroupLimit") == 2


def test_sums_of_vectors_stay_in_generated_code(spark, sf_dir):
    """A row for each client and D sums leave a task, not a row for each sample and coordinate."""
    for name in ("full_gradient", "clipped_gradient"):
        logical, _ = plan_of(catalogue.QUERIES[name](spark, sf_dir))
        below = logical[logical.index("Generate") :]
        assert below.index("Aggregate") < below.index("Relation") and "lambda" not in below


def test_bucketed_tables_join_without_a_shuffle(spark, sf_dir):
    _, physical = plan_of(catalogue.QUERIES["bucketed_join"](spark, sf_dir))
    below = physical[physical.index("SortMergeJoin") :]
    assert "Exchange" not in below and below.count("Bucketed: true") == 2


def test_trainings_run(spark, sf_dir):
    """Every registered training gives a trace of all its runs, with the measures in their ranges."""
    for name in ("train_vec_network", "train_natural_clients", "train_single_node", "train_wide_network"):
        rows = catalogue.QUERIES[name](spark, sf_dir).collect()
        runs = {r["run"] for r in rows}
        assert len(runs) >= 3 and all(0 <= r["accuracy"] <= 1 and 0 <= r["clipped_share"] <= 1 and r["grad_sq"] >= 0 for r in rows)
        assert {r["run"] for r in rows if r["eps"] is None} == {"not_private"}


def test_loader_refuses(spark, tmp_path):
    from hushgrad.sources import tables

    spark.range(3).write.parquet(f"{tmp_path}/region.parquet")
    with pytest.raises(tables.SchemaError):
        tables.load(spark, str(tmp_path), "region")
    bad = spark.sql("SELECT array(1D, double('NaN')) AS v UNION ALL SELECT array(1D) UNION ALL SELECT null")
    with pytest.raises(tables.SchemaError, match="1 null, 1 of another length than 2, 1 with"):
        tables.check_vectors(bad, "v", 2)
