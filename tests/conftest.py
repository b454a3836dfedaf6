import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

from seqvault.session import local_session, ship_package  # noqa: E402


@pytest.fixture(scope="session")
def spark():
    session = local_session(cpus=4, memory="4g", partitions=4)
    ship_package(session)
    yield session


@pytest.fixture(scope="session")
def sf() -> str:
    return "/root/testdata/sf0.001"
