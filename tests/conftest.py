"""One local session for all tests."""

from __future__ import annotations

import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from batchfeed.session import local_session

    base = tmp_path_factory.mktemp("spark")
    s = local_session(8, "4g", **{"spark.sql.warehouse.dir": f"file://{base}/warehouse", "spark.checkpoint.dir": f"file://{base}/shared", "spark.ui.showConsoleProgress": "false", "spark.sql.shuffle.partitions": "2"})
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()
