import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from bitempo.session import build_session

    return build_session(4, memory="4g", partitions=4)


@pytest.fixture(scope="session")
def sf():
    return SF
