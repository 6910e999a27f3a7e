import builtins
import importlib
import sys

import __spark_entry__ as entry


def test_entry_and_names(spark):
    df = entry.entry(spark)
    assert df.columns == ["rid", "cid", "val"] and df.count() == 1
    names = entry.queries()
    assert len(names) > 90 and set(entry.oracle_sql()) <= set(names)


def test_optional_parts_may_be_missing(monkeypatch):
    real = builtins.__import__

    def without(name, *args, **kw):
        if name.startswith(("gridalg.llm", "corpus_pipeline")):
            raise ImportError(name)
        return real(name, *args, **kw)

    for name in [m for m in sys.modules if m.startswith("gridalg.llm") or m == "corpus_pipeline"]:
        monkeypatch.delitem(sys.modules, name)
    import gridalg

    monkeypatch.delattr(gridalg, "llm", raising=False)
    monkeypatch.setattr(builtins, "__import__", without)
    bare = importlib.reload(entry)
    assert "pipeline" not in bare.queries() and not any(n.startswith("op1") for n in bare.queries())
    monkeypatch.undo()
    importlib.reload(entry)
