import pytest

from tests.conftest import spark  # noqa: F401


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"
