"""Every query with a DuckDB twin gives the same rows; the others give what their measures must be."""

import pytest
from comparing import same
from pyspark.errors import AnalysisException

from detspark import catalogue
from detspark.functions.schema import ProblemSpec
from detspark.operators import space

#: workloads that train or sweep for minutes; their steps are tested on smaller problems
SLOW = {"w1_accuracy", "w2_trajectory", "w4_breakdown", "w5_dedup_matrix", "w6_strong", "w7_weak", "w9_memory", "sampling_energy"}
#: rows that the others must give (None: any number above 0)
ROWS = {"couple_screened_budget": 3, "transformer_infer": None, "w5_dedup_skewed": 2, "w10_footprint": 5, "exact_values": 4, "stage_measures": 5, "convergence": 1, "loop_run": 3}


@pytest.mark.parametrize("name", sorted(catalogue.ORACLES))
def test_equals_its_twin(spark, sf, duck, name):
    assert same(catalogue.QUERIES[name](spark, sf).toPandas(), duck.execute(catalogue.ORACLES[name]).fetchdf())


@pytest.mark.parametrize("name", sorted(set(catalogue.QUERIES) - set(catalogue.ORACLES) - SLOW))
def test_gives_its_rows(spark, sf, name):
    n = catalogue.QUERIES[name](spark, sf).count()
    assert n == ROWS[name] if ROWS[name] else n > 0


#: queries that once made their data up
FROM_TABLES = ["exact_values", "first_below", "scaling_efficiency", "space_enumerate", "space_reference", "stage_share", "stage_speedup", "trajectory_diff"]


@pytest.mark.parametrize("name", FROM_TABLES)
def test_needs_its_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        catalogue.QUERIES[name](spark, str(tmp_path)).collect()


def test_exact_values_of_the_table(spark, sf):
    values = {r["problem"]: r["energy"] for r in catalogue.QUERIES["exact_values"](spark, sf).collect()}
    assert abs(values["table_m8_n3"] + 312.511641821) < 1e-6


def test_reference_of_two_words(spark):
    assert [tuple(space.reference(spark, ProblemSpec(84, n)).first()) for n in (6, 65)] == [(63, 0), ((1 << 63) - 1, 3)]


def test_entry_imports(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
