"""The registered experiments run the harness's whole grids; Gaussians reach the block path."""

import inspect

import numpy as np
import pytest

from rowsketch.operators import baselines
from rowsketch.plans import harness, queries
from rowsketch.sources import datagen

CALLS = {"error_report_syn": "error_report", "error_report_doc": "error_report", "error_report_emb": "error_report", "signal_dimension_report": "signal_sweep", "noise_report": "noise_sweep", "merge_report": "merging", "scaling_report": "scaling"}


@pytest.mark.parametrize("name", CALLS)
def test_whole_grids(spark, sf, monkeypatch, name):
    full = inspect.signature(getattr(harness, CALLS[name]))
    made, seen = {}, {}

    def call(*a, **k):
        seen.update(full.bind(*a, **k).arguments)

    monkeypatch.setattr(harness, "synthetic", lambda *a, **k: made.update(args=a[1:], options=k))
    monkeypatch.setattr(harness, "medians", lambda report: report)
    monkeypatch.setattr(harness, CALLS[name], call)
    queries.QUERIES[name](spark, sf)
    for p in ("ms", "noises", "ns", "ds", "parts", "fan_ins", "seeds", "n", "m"):
        assert p not in seen
    assert name == "error_report_doc" or "ells" not in seen
    assert "timing" not in full.parameters or seen["timing"] is True
    if name == "error_report_syn":
        assert seen["d"] == 1000 and made == {"args": (), "options": {}}


def test_gaussians_pass_through(spark):
    a = datagen.signal_noise(spark, 60, 8, 2, 10.0, 1)
    sign, gauss = (baselines.accumulate(a, {"x": ("dense", 5, 3)}, 8, dist=x)["x"] for x in ("sign", "gaussian"))
    rows = a.collect()
    own = baselines.DenseSigns(5, 8, 3, "gaussian")
    own.extend(np.array([r["vec"] for r in rows]), np.array([r["row_id"] for r in rows]))
    assert np.allclose(gauss, own.b) and not np.allclose(gauss, sign)
