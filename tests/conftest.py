import sys
from pathlib import Path

import pytest

sys.path[:0] = [str(Path(__file__).resolve().parents[1])]


@pytest.fixture(scope="session")
def spark():
    from recblock.session import local_session

    s = local_session(4, "tests", 4)
    s.sparkContext.setLogLevel("ERROR")
    return s
