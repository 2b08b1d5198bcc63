import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
os.environ.setdefault("SPARK_LOCAL_IP", "127.0.0.1")

DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from flextensor.session import local_session

    return local_session(2, 4, "4g")


@pytest.fixture(scope="session")
def data():
    return DATA
