"""The library without its text operators."""

import shutil
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent


def test_the_rest_works_without_the_text_operators(tmp_path):
    for name in ("__spark_entry__.py",):
        shutil.copy(ROOT / name, tmp_path)
    shutil.copytree(ROOT / "bitgraph", tmp_path / "bitgraph", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    look = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert set(o) <= set(q) and 'tp_spo' in q and not any(n.startswith('op1_') for n in q); print(len(q))"
    out = subprocess.run([sys.executable, "-c", look], cwd=tmp_path, capture_output=True, text=True, timeout=120, check=False)
    assert out.returncode == 0 and int(out.stdout) > 200, out.stderr[-2000:]
