"""The entry module without the training-data operators, as it must work where they have been taken out."""

import os
import shutil
import subprocess
import sys

from conftest import ROOT


def test_entry_without_training_data_operators(tmp_path):
    skip = shutil.ignore_patterns(".git", "__pycache__", "llm", "spark-warehouse")
    for pipeline in (True, False):
        at = tmp_path / str(pipeline)
        shutil.copytree(ROOT, at, ignore=skip)
        if not pipeline:
            (at / "corpus_pipeline.py").unlink(missing_ok=True)
        code = "import __spark_entry__ as e; q, s = e.queries(), e.oracle_sql(); assert set(s) <= set(q) and len(q) > 100 and not [n for n in q if n == 'pipeline' or n.startswith('op1')]"
        subprocess.run([sys.executable, "-c", code], cwd=at, check=True, env={**os.environ, "PYTHONPATH": str(at)}, timeout=120)
