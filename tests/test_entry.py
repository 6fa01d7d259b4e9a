import pathlib
import re

import __spark_entry__ as entry


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["l_suppkey", "n_items"] and df.count() > 0


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_nothing_imports_the_llm_subpackage():
    root = pathlib.Path(entry.__file__).parent
    for path in [*root.glob("*.py"), *(root / "runstore").rglob("*.py")]:
        if "llm" in path.parts or path.name in ("__spark_entry__.py", "corpus_pipeline.py"):
            continue
        assert not re.search(r"(from|import)\s+runstore\.llm|from runstore import .*\bllm\b", path.read_text()), path
