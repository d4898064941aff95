"""The driver contract: every query agrees with its DuckDB equivalent, and the rest works without the training-data operators."""

import math
import os
import subprocess
import sys

import duckdb
import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
from bitempo import experiments, queries  # noqa: E402

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
assert experiments


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')").fetchall()
    return c


def canonical(df):
    names = sorted(df.columns)

    def text(v):
        if v is None or (isinstance(v, float) and math.isnan(v)):
            return None
        return f"{v:.6f}" if isinstance(v, float) else str(v)

    return names, sorted((tuple(text(v) for v in r) for r in df[names].itertuples(index=False)), key=str)


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_its_oracle(spark, sf, duck, name):
    got = queries.QUERIES[name](spark, sf).toPandas()
    assert canonical(got) == canonical(duck.execute(queries.ORACLES[name]).df())


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0 and set(e.oracle_sql()) <= set(e.queries())


def test_the_rest_imports_without_the_optional_part():
    block = "import sys\nfor m in ('corpus_pipeline', 'bitempo.llm', 'bitempo.llm.queries'): sys.modules[m] = None\nimport __spark_entry__ as e\nq = e.queries()\nassert 'c1_edges' in q and not any(k.startswith('op') or k == 'pipeline' for k in q)\n"
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    subprocess.run([sys.executable, "-c", block], check=True, cwd=root, timeout=120)


def test_nothing_else_imports_the_optional_part():
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    for folder, _, names in os.walk(os.path.join(root, "bitempo")):
        if os.path.basename(folder) in ("llm", "__pycache__"):
            continue
        for n in names:
            if n.endswith(".py"):
                with open(os.path.join(folder, n)) as f:
                    assert "llm" not in f.read(), n
