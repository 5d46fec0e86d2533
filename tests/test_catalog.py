import builtins
import importlib
import sys

import pytest

from affinity_graph import catalog

NAMES = [q for q in catalog.ORACLES if q.startswith(("edges_", "plan_", "generated", "summary_", "clone_", "window_", "ideal_", "chung", "kron", "draw", "topk", "log", "cube", "asof", "blowup", "repeat"))]


@pytest.mark.parametrize("name", NAMES)
def test_equals_duckdb(name, spark, data, same):
    same(catalog.QUERIES[name](spark, data), catalog.ORACLES[name])


def test_entry_without_optional_operators(monkeypatch):
    real = builtins.__import__

    def no_llm(name, *a, **b):
        if name.startswith(("affinity_graph.llm", "corpus_pipeline")):
            raise ModuleNotFoundError(name, name="affinity_graph.llm")
        return real(name, *a, **b)

    monkeypatch.setattr(builtins, "__import__", no_llm)
    monkeypatch.delitem(sys.modules, "__spark_entry__", raising=False)
    entry = importlib.import_module("__spark_entry__")
    assert "flagship" in entry.queries() and not any(q.startswith("op1_") for q in entry.queries())
    monkeypatch.delitem(sys.modules, "__spark_entry__", raising=False)


def test_entry_runs(spark):
    import __spark_entry__

    rows = __spark_entry__.entry(spark).collect()
    assert {r.model for r in rows} == {"original", "model"}
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
