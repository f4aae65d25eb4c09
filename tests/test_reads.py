"""Queries that once made their data up read a stored table."""

import pytest
from support import SF_SMOKE

from navspark.plans import registry

READS = {"hist_native_resolution": "events", "er_macro": "orders", "rank_marks": "orders", "gain_table": "orders", "ablation_means": "orders"}
READS |= {"vocab": "events", "mix_curriculum": "orders", "mix_registry": "orders", "mix_weights": "orders", "nav_registry": "orders"}


@pytest.mark.parametrize("name", sorted(READS))
def test_reads_its_table(spark, name):
    files = registry.queries()[name](spark, SF_SMOKE).inputFiles()
    assert any(f.endswith(f"/{READS[name]}.parquet") for f in files)
