"""Queries that once made their data up read a given table."""

from __future__ import annotations

import pytest

from rankjoin import queries


@pytest.mark.parametrize("name", ["W39", "W44", "syn_uniform"])
def test_reads_a_given_table(spark, sf, name, monkeypatch):
    read = []
    kind = type(spark.read)
    plain = kind.parquet
    monkeypatch.setattr(kind, "parquet", lambda self, *paths, **options: read.extend(p for p in paths if p.startswith(sf)) or plain(self, *paths, **options))
    assert queries.QUERIES[name](spark, sf).count() > 0 and read
