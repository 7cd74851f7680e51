import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from stalegrad.session import local_session, ship

    session = local_session(cores=8, shuffle_partitions=4, memory="6g")
    session.sparkContext.setLogLevel("ERROR")
    session.sparkContext.setCheckpointDir(str(tmp_path_factory.mktemp("stages")))
    return ship(session)


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"
