import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
os.environ.setdefault("PYTHONPATH", str(ROOT))

DATA = "/root/testdata"


@pytest.fixture(scope="session")
def spark():
    from treesketch.session import local_session

    return local_session(os.environ.get("TEST_CPUS", "4"), shuffle_partitions=4, driver_memory="6g")


@pytest.fixture(scope="session")
def tiny():
    return f"{DATA}/sf0.001"
