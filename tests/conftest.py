import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from forkline.session import build_session

    session = build_session("tests", shuffle_partitions=3, local="4", shared=f"file://{tmp_path_factory.mktemp('shared')}")
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def fx(spark):
    """The hand fixture: two components, a cycle in each, and an isolated vertex 10."""
    from forkline.graph import graph_of

    pairs = [(1, 2), (2, 3), (3, 4), (1, 5), (5, 6), (4, 6), (7, 8), (8, 9), (7, 9)]
    return graph_of(spark.createDataFrame(pairs, "a bigint, b bigint"), "fx", vertices=spark.range(1, 11))
