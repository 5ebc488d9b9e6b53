import subprocess
import sys
from pathlib import Path
from shutil import copytree, ignore_patterns

ROOT = Path(__file__).resolve().parent.parent


def test_the_rest_works_without_the_corpus_operators(tmp_path):
    copytree(ROOT / "boxsum", tmp_path / "boxsum", ignore=ignore_patterns("llm", "__pycache__"))
    (tmp_path / "__spark_entry__.py").write_text((ROOT / "__spark_entry__.py").read_text())
    code = "import __spark_entry__ as e; n = e.queries(); assert 'pipeline' not in n and 'm14_area_series' in n and set(e.oracle_sql()) <= set(n)"
    subprocess.run([sys.executable, "-B", "-c", code], cwd=tmp_path, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)}, check=True, timeout=120)


def test_nothing_else_imports_them():
    for path in (ROOT / "boxsum").rglob("*.py"):
        if "llm" not in path.parts:
            assert "llm" not in path.read_text(), path
