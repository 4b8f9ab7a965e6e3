"""Workloads at size: descriptors of an archive are made once."""

from tilemine.operators.tsvq import Stop
from tilemine.plans import queries_index
from tilemine.sources import archives


def test_texts_are_described_once_for_several_indexes(spark, sf, monkeypatch):
    calls, made = [], archives.text_docs
    monkeypatch.setattr(archives, "text_docs", lambda *a: calls.append(1) or made(*a))
    monkeypatch.setattr(queries_index, "_held", {})
    monkeypatch.setattr(queries_index, "_described", {}, raising=False)
    for h in (0, 1):
        queries_index._index(spark, sf, "docs", schedule="hybrid", stop=Stop(h_max=h))
    assert len(calls) == 1
