import os

import pytest

from carepath.session import build, ensure_importable

os.environ.setdefault("TZ", "UTC")


@pytest.fixture(scope="session")
def spark():
    session = build(4, "4g", 4)
    session.sparkContext.setLogLevel("ERROR")
    ensure_importable(session)
    yield session
    session.stop()
