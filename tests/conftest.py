from __future__ import annotations

import pytest

from curvetree.session import local_session

SMALLEST = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    return local_session(8, 4, "6g")


@pytest.fixture(scope="session")
def sf_dir() -> str:
    return SMALLEST
