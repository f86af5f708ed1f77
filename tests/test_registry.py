"""Every query of the engine has SQL and gives the SQL's rows."""

from __future__ import annotations

import pytest

from collidra.plans import registry
from tests.conftest import same_rows

#: Compared at the smallest scale by the driver only: they take a minute each.
SLOW = {"workload_lines", "minwise_signature"}


def test_every_query_has_sql():
    assert set(registry.QUERIES) == set(registry.ORACLES)


@pytest.mark.parametrize("name", sorted(set(registry.ORACLES) - SLOW))
def test_query_equals_sql(name, spark, small, duck):
    same_rows(registry.QUERIES[name](spark, small), duck, registry.ORACLES[name])


def test_entry_gives_the_graph(spark):
    import __spark_entry__

    df = __spark_entry__.entry(spark)
    assert df.columns == ["query_id", "neighbor_id", "rank", "collisions"] and df.count() > 0


def test_entry_works_without_what_the_corpus_part_imports(monkeypatch):
    """A missing library of the corpus subpackage takes its queries away and no others."""
    import builtins
    import sys

    import __spark_entry__

    real = builtins.__import__

    def refuse(name, *args, **kwargs):
        if name in ("zstandard", "corpus_pipeline"):
            raise ImportError(name)
        return real(name, *args, **kwargs)

    for name in [m for m in sys.modules if m.startswith("collidra.llm") or m in ("zstandard", "corpus_pipeline")]:
        monkeypatch.delitem(sys.modules, name)
    import collidra

    monkeypatch.delattr(collidra, "llm", raising=False)
    monkeypatch.setattr(builtins, "__import__", refuse)
    assert set(__spark_entry__.queries()) == set(registry.QUERIES)
