import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

DATA = "/root/testdata"


@pytest.fixture(scope="session")
def spark():
    from mlcurate.session import local_session, prepare

    s = local_session(8, 8, "6g")
    s.sparkContext.setLogLevel("ERROR")
    yield prepare(s)
    s.stop()
