import math

import pytest

from pagesketch import bounds
from pagesketch.config import DELTA, OVERESTIMATE, SIZES_MIB, BufferPlan, PageGeometry, SketchConfig, size_formula


def test_table_of_sizes():
    found = [(c.width, c.depth, c.n) for c in (SketchConfig.from_size(m << 20, DELTA, OVERESTIMATE) for m in SIZES_MIB)]
    assert found == [(3355444, 5, 9875188), (6710887, 5, 19750377), (13421773, 5, 39500754), (26843546, 5, 79001508)]


def test_size_examples():
    assert round(size_formula(2**-26, 0.01) / 1e9, 2) == 3.36
    assert round(size_formula(2**-27, 0.01) / 1e9, 2) == 6.72
    assert (1 << 30) * 2**-26 == 16 and (1 << 31) * 2**-26 == 32


def test_buffers_of_the_four_sizes():
    found = []
    for mib in SIZES_MIB:
        geom = PageGeometry.of(SketchConfig.from_size(mib << 20, DELTA, OVERESTIMATE, family="xx64"), mode="straddling")
        plan = BufferPlan.of(geom, 64 << 23)
        found.append((plan.capacity, round(plan.update_io, 4)))
    assert found == [(51, 0.0195), (25, 0.0391), (12, 0.0781), (6, 0.1563)]


@pytest.mark.parametrize("mode", ["aligned", "straddling"])
def test_default_geometry(mode):
    cfg = SketchConfig.from_stream(60_000, 8, 0.01)
    geom = PageGeometry.of(cfg, mode=mode)
    assert (cfg.width, cfg.depth, geom.pages, geom.columns) == (20388, 5, 200, 102)
    assert geom.total_columns >= cfg.width
    if mode == "aligned":
        assert abs(bounds.page_load(60_000, 200)["load"] - 379.7) < 0.1
        assert abs(bounds.paged(geom, 60_000)["error"] - 10.12) < 0.01


def test_refusals():
    for bad in (dict(eps=0, delta=0.1), dict(eps=0.1, delta=1)):
        with pytest.raises(ValueError):
            SketchConfig(depth=1, width=1, **bad)
    with pytest.raises(ValueError):
        SketchConfig(0.1, 0.1, 3, 1 << 24)
    with pytest.raises(ValueError):
        PageGeometry.of(SketchConfig.from_error(0.01, 0.01), block_bytes=32)


def test_update_cost_is_never_over_one():
    geom = PageGeometry.of(SketchConfig.from_stream(60_000))
    plan = BufferPlan.of(geom, 1000)
    assert plan.raw_update_io > 1 and plan.update_io == 1 and plan.capacity == 1


def test_predictions_for_unique_keys():
    flat = bounds.predicted_flat(60_000, 20388, 5)
    paged = bounds.predicted_paged(60_000, 200, 102, 5)
    assert abs(flat["avg_over"] - 1.1365) < 1e-3 and abs(flat["zero_share"] - 0.237) < 2e-3
    assert abs(paged["avg_over"] - 1.1428) < 3e-3


def test_tail_bound_and_policies():
    assert bounds.binomial_tail(1000, 0.5, 500) == 1.0
    assert bounds.binomial_tail(1000, 0.5, 600) < 1e-8
    widths = [SketchConfig.from_policy(10**6, p).width for p in ("n_over_log_n", "n_pow_3_4", "sqrt_n", "constant")]
    assert widths == sorted(widths)
    assert math.isclose(SketchConfig.from_policy(10**6, "sqrt_n").eps, 1e-3)


def test_fingerprints_tell_configurations_apart():
    a, b = SketchConfig.from_stream(1000), SketchConfig.from_stream(1001)
    assert a.fingerprint() != b.fingerprint() and a.fingerprint() == SketchConfig.from_stream(1000).fingerprint()
