"""Queries whose jobs moved onto given tables read them in Spark."""

import pytest

from assetmill import workloads

NAMES = """src_python w09_mixture w10_crops w10_token_counts w14_capacity w14_capacity_compare w15_timestep_embedding w16_placement w17_ortho_loss w19_lr w19_sparse_merge""".split()


@pytest.mark.parametrize("name", NAMES)
def test_spark_reads_a_table(spark, name):
    assert workloads.queries()[name](spark, "/root/testdata/sf0.001").inputFiles()
