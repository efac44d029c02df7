import importlib
import sys


def test_entry_and_registry(spark):
    import __spark_entry__ as e

    assert [tuple(r) for r in e.entry(spark).orderBy("dist").collect()][0] == (0, 1)
    queries, sql = e.queries(), e.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 100


def test_imports_without_the_corpus_operators(monkeypatch):
    for name in [n for n in sys.modules if n.startswith("sparkgraphs.llm") or n in ("corpus_pipeline", "__spark_entry__")]:
        monkeypatch.delitem(sys.modules, name)
    monkeypatch.setitem(sys.modules, "sparkgraphs.llm", None)
    e = importlib.import_module("__spark_entry__")
    assert e.corpus is None and not [q for q in e.queries() if q[:3] in ("op1", "op2")]
    monkeypatch.delitem(sys.modules, "__spark_entry__")
