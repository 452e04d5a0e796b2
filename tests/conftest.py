import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"


@pytest.fixture(scope="session")
def spark():
    from neardup.session import get_session

    session = get_session("4", 4)
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()
