"""Queries that made their rows up now read a given table: they agree with their SQL, and their plans or jobs scan a table."""

import pytest

from gnnspark.queries import registry

NAMES = "early_stop_point bce_loss delays divergence_curve exchange_bytes grad_mean grad_mean_equals_fold grad_running_mean interval_overlap params_init queue_bound_ok queue_size"


@pytest.mark.parametrize("name", NAMES.split())
def test_reads_a_given_table(spark, sf, duck, same, name, monkeypatch):
    seen, parquet = [], type(spark.read).parquet
    monkeypatch.setattr(type(spark.read), "parquet", lambda self, *paths, **more: seen.extend(paths) or parquet(self, *paths, **more))
    same(registry.queries()[name](spark, sf), duck.sql(registry.oracles()[name]))
    assert seen
