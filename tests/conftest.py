import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))


@pytest.fixture(scope="session")
def spark():
    from embedvocab.session import build

    return build("tests", cores=4, partitions=4)


@pytest.fixture(scope="session")
def smoke():
    return "/root/testdata/sf0.001"
