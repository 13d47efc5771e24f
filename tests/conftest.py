import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))


@pytest.fixture(scope="session")
def spark():
    import os

    os.environ["PYTHONPATH"] = str(Path(__file__).resolve().parent.parent) + ":" + os.environ.get("PYTHONPATH", "")
    from idagg.session import get_session

    return get_session(4, 4, spark__driver__memory="4g")


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"
