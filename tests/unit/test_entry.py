"""The driver contract, and that the package works without its optional folder."""

import pathlib
import shutil
import subprocess
import sys

ROOT = pathlib.Path(__file__).resolve().parents[2]


def test_entry_and_names(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    rows = e.entry(spark).collect()
    assert rows and all(r["accepted"] for r in rows)


def test_imports_without_the_text_operators(tmp_path):
    shutil.copytree(ROOT / "mapmatch", tmp_path / "mapmatch", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'doc_email_rows' in q and 'pipeline' not in q and not any(n.startswith('op') for n in q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": ":".join(p for p in sys.path if p and p != str(ROOT))})


def test_nothing_outside_imports_the_text_operators():
    for path in (ROOT / "mapmatch").rglob("*.py"):
        if "llm" not in path.parts:
            assert "llm" not in path.read_text(), path
