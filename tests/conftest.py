import pytest

from tauprobe.session import build_session


@pytest.fixture(scope="session")
def spark():
    session = build_session("tests")
    session.sparkContext.setLogLevel("ERROR")
    return session
