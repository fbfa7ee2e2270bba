"""Queries of functions in SQL take whole tables."""

import pytest
from pyspark.errors import AnalysisException

import __spark_entry__ as entry
from curvature_spark.sources.synthetic import SyntheticProblem


@pytest.mark.parametrize("name", ["sql_functions", "udtf_sparse_to_rows"])
def test_every_vector_is_in_the_answer(spark, small, name):
    want = spark.read.parquet(f"{small}/embeddings.parquet").select("vec_id").distinct().count()
    assert entry.queries()[name](spark, small).select("vec_id").distinct().count() == want


def test_joins_take_every_customer_and_order(spark, small):
    orders, customers = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("orders", "customer"))
    assert entry.queries()["join_inner"](spark, small).count() == orders.count()
    rows = entry.queries()["join_full"](spark, small)
    assert rows.select("c_custkey").na.drop().distinct().count() == customers.count()
    assert entry.queries()["join_anti"](spark, small).count() == orders.where("o_orderstatus <> 'F'").count() > 0


@pytest.mark.parametrize(
    "name",
    ["comm_bytes_model", "compressor_bias_variance", "compressor_diagnostics", "cost_model", "experiment_estimate", "experiment_indices", "experiment_tight_expectation", "experiment_window_locality", "synthetic_source"],
)
def test_figures_come_from_a_given_table(spark, tmp_path, name):
    """Without the tables there is no answer."""
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        entry.queries()[name](spark, str(tmp_path)).collect()


def test_synthetic_rows_depend_on_their_number_alone(spark):
    spark.dataSource.register(SyntheticProblem)
    read = lambda parts: spark.read.format("synthetic_problem").option("rows", 40).option("partitions", parts).load().orderBy("sample_key").collect()
    assert read(1) == read(4) and len(read(4)) == 40
