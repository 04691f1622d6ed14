"""The driver's contract, and that the engine stands without the text operators."""

from __future__ import annotations

import ast
import subprocess
import sys
from pathlib import Path

import __spark_entry__ as contract
import pytest

ROOT = Path(__file__).resolve().parents[1]
SMOKE = ["b7_block_stats_lineitem", "s3_block_leverage_documents", "k1_draws_replacement", "g2_gradient", "g11_coded_descent_documents", "r_rollup_stats"]


def test_every_oracle_has_a_query():
    assert set(contract.oracle_sql()) <= set(contract.queries())
    assert len(contract.queries()) >= 110


def test_entry_has_rows(spark):
    assert contract.entry(spark).count() == 7


@pytest.mark.parametrize("name", SMOKE)
def test_query_equals_oracle(spark, sf_dir, name):
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        path = Path(f"{sf_dir}/{t}.parquet")
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path}{'/*.parquet' if path.is_dir() else ''}')")
    out = contract.queries()[name](spark, sf_dir)
    cursor = con.execute(contract.oracle_sql()[name])
    names = [c[0] for c in cursor.description]
    assert sorted(names) == sorted(out.columns)
    got = sorted(map(str, (tuple(r[c] for c in sorted(names)) for r in out.collect())))
    want = sorted(map(str, (tuple(r[names.index(c)] for c in sorted(names)) for r in cursor.fetchall())))
    assert got == want


def test_nothing_outside_imports_the_text_operators():
    for p in (ROOT / "blocksketch").rglob("*.py"):
        if "llm" in p.relative_to(ROOT).parts:
            continue
        for node in ast.walk(ast.parse(p.read_text())):
            names = [a.name for a in node.names] if isinstance(node, ast.Import) else [node.module or ""] if isinstance(node, ast.ImportFrom) else []
            assert not any(".llm" in n or n == "corpus_pipeline" for n in names), p


def test_contract_without_the_text_operators(tmp_path):
    import shutil

    shutil.copytree(ROOT / "blocksketch", tmp_path / "blocksketch", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); print(len(q), any(k.startswith('op') or k == 'pipeline' for k in q))"
    out = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path), "HOME": str(tmp_path)})
    n, has = out.stdout.split()
    assert int(n) >= 110 and has == "False"
