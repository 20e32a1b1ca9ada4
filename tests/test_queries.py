"""Every query with SQL gives the same rows as that SQL on the small tables; the library works without the corpus operators."""

from __future__ import annotations

import math
import subprocess
import sys

import duckdb
import pytest

from rangegraph.registry import ORACLES, QUERIES
from rangegraph.sources.tables import NAMES


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else float(f"{v:.9g}") + 0.0
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return v


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for n in NAMES:
        con.execute(f"CREATE VIEW {n} AS SELECT * FROM '{small}/{n}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, duck, small, name):
    df = QUERIES[name](spark, small)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    res = duck.execute(ORACLES[name])
    names = [d[0] for d in res.description]
    want = sorted((tuple(plain(r[names.index(c)]) for c in cols) for r in res.fetchall()), key=repr)
    assert sorted(names) == cols
    assert got == want


def test_without_corpus_operators(tmp_path):
    """The entry module imports, and lists the other queries, where the corpus operators are gone."""
    import shutil
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    shutil.copytree(root / "rangegraph", tmp_path / "rangegraph", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); o = e.oracle_sql(); assert len(q) > 100 and not [n for n in q if n.startswith('op')]; assert set(o) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "HOME": str(tmp_path)})


def test_a_broken_corpus_operator_is_shown(tmp_path):
    """Only their absence is passed over: an operator whose library is missing fails loudly."""
    import shutil
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    if not (root / "rangegraph" / "llm").exists():
        pytest.skip("the corpus operators are gone")
    shutil.copytree(root / "rangegraph", tmp_path / "rangegraph", ignore=shutil.ignore_patterns("__pycache__"))
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    (tmp_path / "ahocorasick.py").write_text("raise ImportError('broken')")
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__"], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "HOME": str(tmp_path), "PYTHONPATH": str(tmp_path)})
    assert done.returncode and "broken" in done.stderr


def test_nothing_else_imports_the_corpus_operators():
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent / "rangegraph"
    for f in root.rglob("*.py"):
        if "llm" not in f.parts:
            assert "llm" not in f.read_text(), f
