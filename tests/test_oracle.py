"""Every query of the reference's own methods against its oracle on the smallest tables."""

import pytest
from oracle import difference, spark_rows

from qacurate.queries import REGISTRY


@pytest.mark.parametrize("name", sorted(REGISTRY.oracles))
def test_equals_oracle(spark, sf, name):
    assert difference(REGISTRY.queries[name](spark, sf), REGISTRY.oracles[name], sf) == ""


@pytest.mark.parametrize("name", ["lsh_pairs_estimated", "dedup_ml", "decontam_ngram_share", "stream_dedup", "stream_late", "textbook_recipe", "mixture_recipe", "extraction_report"])
def test_runs_with_rows(spark, sf, name):
    assert sum(spark_rows(REGISTRY.queries[name](spark, sf))[1].values()) > 0


def test_entry_points():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert "dedup_minhash" in e.queries()
