from __future__ import annotations

import pytest

from freqspark.session import local_session


@pytest.fixture(scope="session")
def spark():
    session = local_session(4, **{"spark.sql.shuffle.partitions": "4"})
    yield session
    session.stop()


@pytest.fixture(scope="session")
def sf_small() -> str:
    return "/root/testdata/sf0.001"
