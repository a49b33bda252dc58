"""The driver contract holds with and without the training-data folders."""

import shutil
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]
NAMES = "import __spark_entry__ as e; q = e.queries(); o = e.oracle_sql(); print(len(q), 'pipeline' in q, any(n.startswith('op3_') for n in q), set(o) <= set(q))"


def names(root):
    done = subprocess.run([sys.executable, "-B", "-c", NAMES], cwd=root, env={"PYTHONPATH": str(root), "PATH": "/usr/bin:/bin"}, capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr[-2000:]
    return done.stdout.split()


def test_queries_without_the_training_data_folders(tmp_path):
    for left in ((), ("corpus_pipeline.py",), ("corpuskit/llm/__init__.py",)):
        root = tmp_path / f"copy{len(left)}{left[0][-5:-3] if left else ''}"
        shutil.copytree(ROOT, root, ignore=shutil.ignore_patterns(".git", "__pycache__", "llm"))
        for name in left:
            if name == "corpus_pipeline.py":
                (root / name).unlink()
            else:  # an empty folder is left
                (root / name).parent.mkdir()
        n, pipeline, op3, covered = names(root)
        assert int(n) > 200 and (pipeline, op3, covered) == ("False", "False", "True")
