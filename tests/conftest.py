import os
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))
os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

DATA = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark():
    from rulegraph.session import local_session, ship

    session = ship(local_session(4, 4, "4g", "tests"))
    yield session
    session.stop()


@pytest.fixture(scope="session")
def sf_dir():
    return DATA
