"""Meters and counters that need no Spark session."""

import numpy as np
import pytest

from boolmat.formats.base import Tile, columns_of, pack_columns
from boolmat.formats.registry import FORMATS
from boolmat.metrics import measures


def test_counters_are_read_from_perf(tmp_path, monkeypatch):
    tool = tmp_path / "perf"
    tool.write_text("#!/bin/bash\ntrap 'echo \"900,,cycles,1,100\" >&2; echo \"300,,instructions:u,1,100\" >&2; echo \"<not supported>,,LLC-loads,0,0\" >&2; exit 0' INT\ntouch \"$(dirname \"$0\")/up\"\nwhile true; do sleep 0.05; done\n")
    tool.chmod(0o755)
    monkeypatch.setenv("PATH", f"{tmp_path}:/usr/bin:/bin")
    meter = measures.HardwareCounters()
    meter.start()
    for _ in range(100):
        if (tmp_path / "up").exists():
            break
        import time

        time.sleep(0.05)
    got = meter.stop()
    assert got["cycles"] == 900 and got["instructions"] == 300 and got["cpi"] == 3 and got["l3_accesses"] is None and got["reason"] is None


def test_counters_without_perf(monkeypatch):
    monkeypatch.setenv("PATH", "/nowhere")
    meter = measures.HardwareCounters()
    meter.start()
    got = meter.stop()
    assert got["cycles"] is None and got["reason"] == "no perf on this host"


@pytest.mark.parametrize("columns", [[], [5], [5, 6, 7], [0, 3, 10**12], list(range(100)), [2, 9, 10, 4000]])
def test_column_dictionaries(columns):
    own = np.array(columns, np.int64)
    packed = pack_columns(own)
    assert np.array_equal(columns_of(packed), own) and (len(columns) < 100 or len(packed) == 17)


@pytest.mark.parametrize("name", FORMATS)
def test_every_format_counts_what_a_product_touches(name):
    _, work = FORMATS[name].encode(Tile(5, 4, np.array([0, 0, 0, 1, 1, 2, 2, 2, 3]), np.array([0, 1, 3, 0, 1, 0, 1, 3, 2])))
    assert work["touched"] > 0
