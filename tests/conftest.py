import os
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
os.environ.setdefault("WEBTEXT_DRIVER_MEMORY", "4g")


@pytest.fixture(scope="session")
def spark():
    from webtext.session import local

    s = local(8, 4)
    s.sparkContext.setLogLevel("ERROR")
    return s
