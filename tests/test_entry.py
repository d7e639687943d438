"""The entry module without the training-data folders, and without a folder for shared tables."""

import shutil
import subprocess
import sys
from pathlib import Path

import pytest

from filterfleet.functions import frames

ROOT = Path(__file__).resolve().parent.parent


@pytest.mark.parametrize("with_pipeline", [False, True])
def test_entry_without_the_training_operators(tmp_path, with_pipeline):
    shutil.copytree(ROOT / "filterfleet", tmp_path / "filterfleet", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    if with_pipeline:
        (tmp_path / "corpus_pipeline.py").write_text("from filterfleet.llm import common\n")
    code = "import __spark_entry__ as e; assert 'tree_search_bulk' in e.queries() and 'pipeline' not in e.queries() and set(e.oracle_sql()) <= set(e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)


def test_a_cluster_needs_a_shared_folder():
    class Nothing:
        isDefined = staticmethod(lambda: False)

    class Session:
        """A session on a cluster without a folder."""

        conf = {}

        class sparkContext:
            master = "spark://host:7077"

            class _jsc:
                sc = staticmethod(lambda: type("C", (), {"getCheckpointDir": staticmethod(Nothing)}))

    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        frames.shared_dir(Session)
