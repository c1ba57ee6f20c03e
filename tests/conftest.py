import os
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
DATA = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark():
    from reelspark.session import session

    return session(cpus=8, shuffle=4, memory="6g")


@pytest.fixture(scope="session")
def sf_dir():
    return DATA
