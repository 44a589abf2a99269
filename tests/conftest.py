import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from canopy.session import local_session

    folder = tmp_path_factory.mktemp("shared")
    return local_session(4, 4, **{"spark.checkpoint.dir": f"file://{folder}", "spark.sql.warehouse.dir": f"{folder}/warehouse"})


@pytest.fixture(autouse=True)
def no_stages_left(request):
    yield
    if "spark" in request.fixturenames:
        from canopy.storage import clear

        clear(request.getfixturevalue("spark"))
