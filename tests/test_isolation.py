"""The library without its training-data subpackage."""

import os
import shutil
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent


def _copy(tmp_path: Path) -> Path:
    at = tmp_path / "copy"
    shutil.copytree(ROOT, at, ignore=shutil.ignore_patterns(".git", "__pycache__", ".pytest_cache"))
    return at


def _names(at: Path) -> tuple[list[str], list[str]]:
    code = "import __spark_entry__ as e; print(' '.join(e.queries())); print(' '.join(e.oracle_sql()))"
    out = subprocess.run([sys.executable, "-c", code], cwd=at, env={**os.environ, "PYTHONPATH": str(at)}, capture_output=True, text=True, check=True).stdout
    first, second = out.strip().split("\n")[-2:]
    return first.split(), second.split()


def test_queries_without_the_subpackage(tmp_path):
    at = _copy(tmp_path)
    whole, oracles = _names(at)
    for left in ([], ["corpus_pipeline.py"]):
        for folder in ("purchase_planner/llm", "tests/llm"):
            shutil.rmtree(at / folder, ignore_errors=True)
        for name in left:
            (at / name).unlink(missing_ok=True)
        rest, kept = _names(at)
        own = {q for q in whole if q == "pipeline" or (q.startswith("op") and q[2].isdigit())}
        assert set(rest) == set(whole) - own
        assert set(kept) == set(oracles) - own


def test_nothing_else_imports_the_subpackage():
    for f in (ROOT / "purchase_planner").rglob("*.py"):
        if "llm" not in f.relative_to(ROOT).parts:
            lines = [x for x in f.read_text().split("\n") if x.lstrip().startswith(("import ", "from "))]
            assert not any("llm" in x for x in lines), f
