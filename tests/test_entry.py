"""The entry points, with and without the training-data operators."""

import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent


def test_flagship_and_names(spark):
    import __spark_entry__ as e

    rows = e.entry(spark).collect()
    assert rows and set(rows[0].asDict()) == {"category", "value", "vec"}
    assert set(e.oracle_sql()) <= set(e.queries()) and len(e.queries()) > 140


def test_the_rest_stands_without_the_training_data_operators(tmp_path):
    import shutil

    for name in ("tablevec", "__spark_entry__.py"):
        source = ROOT / name
        (shutil.copytree if source.is_dir() else shutil.copy)(source, tmp_path / name)
    shutil.rmtree(tmp_path / "tablevec" / "llm", ignore_errors=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 140 and 'pipeline' not in q and not any(k[:3] == 'op1' and k[3:4].isdigit() for k in q); e.oracle_sql()"
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path), "HOME": str(tmp_path)})
    assert done.returncode == 0, done.stderr


def test_nothing_outside_imports_the_operators():
    for path in (ROOT / "tablevec").rglob("*.py"):
        if "llm" not in path.parts:
            assert "tablevec.llm" not in path.read_text(), path
