"""The entry point without the optional parts: run in a copy, so that nothing of this process is imported."""

import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent


@pytest.mark.parametrize("gone", [["gridmask/llm", "tests/llm"], ["corpus_pipeline.py"], ["gridmask/llm", "tests/llm", "corpus_pipeline.py"]])
def test_imports_without_optional_parts(tmp_path, gone):
    copy = tmp_path / "copy"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse", *[Path(g).name for g in gone]))
    code = "import __spark_entry__ as e; q, s = e.queries(), e.oracle_sql(); assert set(s) <= set(q) and 'range_2d_10' in q and 'pipeline' not in q; print(sum(n.startswith('op') and n[2].isdigit() for n in q))"
    out = subprocess.run([sys.executable, "-c", code], cwd=copy, capture_output=True, text=True, timeout=120, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(copy)})
    assert out.returncode == 0, out.stderr
    assert (int(out.stdout) > 0) == ("gridmask/llm" not in gone)
