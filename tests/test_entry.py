"""The repository without its training-data subpackage."""

import os
import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
ELSEWHERE = os.environ | {"PYTHONPATH": os.pathsep.join(x for x in os.environ.get("PYTHONPATH", "").split(os.pathsep) if x and Path(x).resolve() != ROOT)}
CODE = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert 'd1_r_cheb4' in q or len(q) > 100; print(sum(n.startswith('op') and n[2].isdigit() or n == 'pipeline' for n in q), set(o) - set(q))"


@pytest.mark.parametrize("gone", [(), ("rowblock/llm",), ("rowblock/llm", "corpus_pipeline.py"), ("corpus_pipeline.py",)])
def test_import_without(tmp_path, gone):
    """What is left still registers its queries; nothing of the deleted parts does."""
    if not (ROOT / "rowblock/llm").exists():
        pytest.skip("already taken out")
    for name in ("__spark_entry__.py", "corpus_pipeline.py"):
        shutil.copy(ROOT / name, tmp_path / name)
    shutil.copytree(ROOT / "rowblock", tmp_path / "rowblock", ignore=shutil.ignore_patterns("__pycache__"))
    for name in gone:
        target = tmp_path / name
        shutil.rmtree(target) if target.is_dir() else target.unlink()
    run = subprocess.run([sys.executable, "-c", CODE], cwd=tmp_path, env=ELSEWHERE, capture_output=True, text=True)
    assert run.returncode == 0, run.stderr[-2000:]
    want = 11 - 10 * ("rowblock/llm" in gone) - (bool(gone))
    assert run.stdout.split()[0] == str(want) and "set()" in run.stdout


def test_other_import_errors_are_not_hidden(tmp_path):
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    shutil.copytree(ROOT / "rowblock", tmp_path / "rowblock", ignore=shutil.ignore_patterns("__pycache__"))
    (tmp_path / "corpus_pipeline.py").write_text("import no_such_module\n")
    run = subprocess.run([sys.executable, "-c", "import __spark_entry__"], cwd=tmp_path, env=ELSEWHERE, capture_output=True, text=True)
    assert run.returncode and "no_such_module" in run.stderr
