"""The library without the training-text part: both folders deleted, with and without the pipeline file."""

import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]


@pytest.mark.parametrize("with_pipeline", [True, False])
def test_library_without_the_training_text_part(tmp_path, with_pipeline):
    copy = tmp_path / "repo"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", ".pytest_cache"))
    shutil.rmtree(copy / "blockwright" / "llm", ignore_errors=True)
    shutil.rmtree(copy / "tests" / "llm", ignore_errors=True)
    if not with_pipeline:
        (copy / "corpus_pipeline.py").unlink(missing_ok=True)
    code = (
        "import __spark_entry__ as e, pathlib, importlib\n"
        "q, o = e.queries(), e.oracle_sql()\n"
        "assert set(o) <= set(q) and len(q) > 60 and not [k for k in q if k.startswith('op') and k[2].isdigit()] and 'pipeline' not in q\n"
        "for f in pathlib.Path('blockwright').rglob('*.py'):\n"
        "    importlib.import_module('.'.join(f.with_suffix('').parts).removesuffix('.__init__'))\n"
    )
    done = subprocess.run([sys.executable, "-c", code], cwd=copy, capture_output=True, text=True)
    assert done.returncode == 0, done.stderr
