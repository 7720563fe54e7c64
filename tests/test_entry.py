import shutil
import subprocess
import sys
from pathlib import Path

import __spark_entry__ as E

ROOT = Path(__file__).resolve().parents[1]


def test_entry(spark):
    df = E.entry(spark)
    assert df.count() > 0 and df.columns == ["region", "level", "value"]


def test_oracles_name_queries():
    assert set(E.oracle_sql()) <= set(E.queries())


def test_library_stands_without_the_training_data_part(tmp_path):
    for name in ("cdfblend", "__spark_entry__.py"):
        src = ROOT / name
        shutil.copytree(src, tmp_path / name, ignore=shutil.ignore_patterns("llm", "__pycache__")) if src.is_dir() else shutil.copy(src, tmp_path / name)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 150 and not any(n.startswith('op1') for n in q) and 'pipeline' not in q; assert set(e.oracle_sql()) <= set(q)"
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin:/usr/local/bin", "HOME": str(tmp_path)})
    assert done.returncode == 0, done.stderr
