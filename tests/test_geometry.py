import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from attention_engine.functions.distance import diversity_np, geo_distance_np
from attention_engine.functions.geometry import area_np, chain_hull, clip, quickhull
from attention_engine.functions.projection import ViewPort, samples_for_distance
from attention_engine.operators.highlights import greedy

PLACES = st.lists(st.tuples(st.integers(-20, 20), st.integers(-20, 20)), min_size=1, max_size=30)


def same(a, b):
    return {tuple(x) for x in a.tolist()} == {tuple(x) for x in b.tolist()}


@settings(max_examples=150, deadline=None)
@given(PLACES)
def test_hulls_agree_and_cover(rows):
    points = np.array(rows, float)
    quick, chain = quickhull(points), chain_hull(points)
    assert abs(area_np(quick) - area_np(chain)) < 1e-9
    if area_np(chain) > 0:
        assert same(quick, chain)
        for a, b in zip(chain, np.roll(chain, -1, axis=0), strict=True):
            assert ((b[0] - a[0]) * (points[:, 1] - a[1]) - (b[1] - a[1]) * (points[:, 0] - a[0]) >= 0).all()


@settings(max_examples=100, deadline=None)
@given(PLACES, PLACES)
def test_overlap_is_symmetric_and_small(a, b):
    p, q = chain_hull(np.array(a, float)), chain_hull(np.array(b, float))
    if len(p) > 2 and len(q) > 2:
        one, two = area_np(clip(p, q)), area_np(clip(q, p))
        assert abs(one - two) < 1e-6
        assert one <= min(area_np(p), area_np(q)) + 1e-6


def test_distances():
    assert geo_distance_np(48.0, 2.0, 48.0, 2.0) == 0
    assert abs(geo_distance_np(0.0, 0.0, 0.0, 180.0) - 20015.09) < 0.01
    assert abs(geo_distance_np(0.0, 0.0, 90.0, 0.0) - 10007.54) < 0.01
    assert abs(geo_distance_np(10.0, 179.9, 10.0, -179.9) - geo_distance_np(10.0, -0.1, 10.0, 0.1)) < 1e-9
    metre = 1 / 111194.93
    assert abs(geo_distance_np(48.0, 2.0, 48.0 + metre, 2.0) - 0.001) < 1e-8
    assert abs(geo_distance_np(48.0, 2.0, 48.5, 2.5) - geo_distance_np(48.0, 2.0, 48.5, 2.5, "cosine_law")) < 1e-6


def test_literal_distance_equation_is_unusable():
    """Read literally, the printed equation isn't 0 from a place to itself."""
    lat, lon = np.radians(48.8584), np.radians(2.2945)
    literal = (np.arccos(np.cos(lat) ** 2 * np.cos(lon)) * np.cos(lon) + np.cos(lat) * np.sin(lat) * np.cos(lon) * np.sin(lon) + np.sin(lat) ** 2) * 6371
    assert literal > 1000


def test_viewport():
    view = ViewPort()
    assert abs(view.x(view.lon(123.0)) - 123.0) < 1e-6 and abs(view.y(view.lat(-45.0)) + 45.0) < 1e-6
    with pytest.raises(ValueError):
        ViewPort(center_lat=90.0)
    assert samples_for_distance(1, 1600) == 630


@pytest.mark.parametrize("swap", ["first", "best", "worst_out"])
def test_greedy_improves_with_budget(swap):
    rng = np.random.default_rng(1)
    lat, lon = 48 + rng.random(200) / 10, 2 + rng.random(200) / 10
    last = -1.0
    for scans in (0, 5, 50, None):
        at, _, _ = greedy(lat, lon, 5, scans, None, swap)
        d = diversity_np(lat[at], lon[at])
        assert d >= last - 1e-12 and len(set(at)) == 5
        last = d
    assert greedy(lat, lon, 5, 0)[0] == list(range(5))


def test_greedy_corner_cases():
    lat, lon = np.array([0.0, 0, 1, 1, 0.5]), np.array([0.0, 1, 0, 1, 0.5])
    assert sorted(greedy(lat[[4, 0, 3, 1, 2]], lon[[4, 0, 3, 1, 2]], 2)[0]) in ([1, 2], [3, 4])
    assert greedy(lat, lon, 9)[0] == list(range(5))
    assert greedy(lat, lon, 1) == ([0], 0, 0)
    same_place = np.zeros(10)
    assert greedy(same_place, same_place, 3)[2] == 0
