import pytest

from multiway.session import local_session


@pytest.fixture(scope="session")
def spark():
    return local_session(8, 8, "6g")


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"
