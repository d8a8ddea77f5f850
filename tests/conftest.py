import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

from waysite.session import local_session, ship_code  # noqa: E402

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    session = local_session(8, 8)
    ship_code(session)
    return session


@pytest.fixture(scope="session")
def sf_dir():
    return SF
