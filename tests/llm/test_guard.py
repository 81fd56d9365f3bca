"""Everything else works without this subpackage."""

import re
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[2]


def test_nothing_else_imports_it():
    for f in (ROOT / "tiersort").rglob("*.py"):
        if "llm" not in f.parts:
            assert not re.search(r"^\s*(from|import) tiersort\.llm", f.read_text(), re.M), f


def test_entry_without_it(tmp_path):
    import shutil

    for name in ("tiersort", "__spark_entry__.py"):
        src = ROOT / name
        (shutil.copytree(src, tmp_path / name, ignore=shutil.ignore_patterns("llm", "__pycache__")) if src.is_dir() else shutil.copy(src, tmp_path / name))
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 80 and not any(x.startswith('op') or x == 'pipeline' for x in q); e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
