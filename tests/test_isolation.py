import shutil
import subprocess
import sys
from pathlib import Path

REPO = Path(__file__).resolve().parents[1]


def test_core_without_the_corpus_package(tmp_path):
    """With conflate/llm gone (or an empty folder left) the entry module imports and lists the core's queries."""
    for name in ("conflate", "__spark_entry__.py", "corpus_pipeline.py"):
        if (REPO / name).is_dir():
            shutil.copytree(REPO / name, tmp_path / name, ignore=shutil.ignore_patterns("llm", "__pycache__"))
        elif (REPO / name).exists():
            shutil.copy(REPO / name, tmp_path / name)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert 'pipeline_wsa' in q and set(o) <= set(q) and not any(x.startswith('op1_') or x == 'pipeline' for x in q)"
    for _ in range(2):
        subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, timeout=120)
        (tmp_path / "conflate/llm").mkdir(exist_ok=True)
