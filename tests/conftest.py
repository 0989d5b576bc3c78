import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from walkstream.session import local_session, ship

    session = local_session("8", 2)
    for key, value in {"spark.sql.adaptive.enabled": "false", "spark.sql.codegen.cache.maxEntries": "2000", "spark.sql.ui.explainMode": "simple"}.items():
        try:
            session.conf.set(key, value)  # small frames: planning by stages costs more than it saves
        except Exception:  # noqa: BLE001  (a setting that is fixed at start)
            continue
    ship(session)
    yield session
    session.stop()
