import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

TESTDATA = "/root/testdata"


@pytest.fixture(scope="session")
def spark():
    from motifjoin.session import local_session

    session = local_session(8, "tests", 8)
    yield session
    session.stop()


@pytest.fixture(scope="session")
def sf(request):
    return f"{TESTDATA}/sf0.001"
