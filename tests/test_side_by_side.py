"""Kernels take many inputs side by side; each one's trace and result are what it has alone."""

from __future__ import annotations

import numpy as np
import pytest

from oblivspark.functions import kernels as K
from oblivspark.operators.permute import spread
from oblivspark.plans import params, trace

METHODS = ("bitonic sort", "bitonic sort, recursive", "layered router", "recursive router")


@pytest.mark.parametrize("method", METHODS)
def test_views_of_many_inputs(method):
    """one call for many blocks, with the trace of one."""
    p, x = params.from_length(256), np.random.default_rng(1).integers(0, 99, (5, 256)).astype(np.uint64)
    assert trace.kernel_view(method, x, p) == trace.simulate_view(method, 256, p) == trace.kernel_view(method, x[3], p)


@pytest.mark.parametrize("level", ["memory", "cluster"])
@pytest.mark.parametrize("route", [K.route_layered, K.route_recursive])
@pytest.mark.parametrize("bits, radix", [(4, 3), (5, 2), (3, 3)])
def test_routers_side_by_side(route, level, bits, radix):
    r, n, z = 3, 40 << bits - 3, 64
    rng = np.random.default_rng(bits)
    rec = rng.integers(0, 256, (r * n, 11)).astype(np.uint8)
    s = K.Slab(np.arange(r * n, dtype=np.uint64)[:, None].copy(), np.ones(r * n, bool), rec)
    full = spread(s, 1 << bits, z, r)
    size = z << bits
    label = rng.integers(0, 1 << bits, r * size)
    got = route(full, label, bits, radix, z, level, K.Meter(blocks=r))
    for i in range(r):
        here = slice(i * size, (i + 1) * size)
        one = route(full.take(here), label[here], bits, radix, z, level)
        for a, b in ((got.words, one.words), (got.real, one.real), (got.rec, one.rec)):
            assert (a[here][got.real[here]] == b[one.real]).all() if a.ndim > 1 else (a[here] == b).all()


@pytest.mark.parametrize("near", [64, 1 << 17])
@pytest.mark.parametrize("ascending", [True, False])
def test_network_layer_by_layer(near, ascending, monkeypatch):
    """The layers together do to words, flags and bytes what they do one by one."""
    monkeypatch.setattr(K, "NEAR", near)
    rng = np.random.default_rng(2)
    for m, words, width in ((2, 1, 3), (16, 3, 9), (64, 2, 0), (64, 1, 8)):
        n = 5 * m
        a = K.Slab(rng.integers(0, 3, (n, words)).astype(np.uint64), rng.integers(0, 2, n) == 1, rng.integers(0, 256, (n, width)).astype(np.uint8))
        b = K.Slab(a.words.copy(), a.real.copy(), a.rec.copy())
        run, one, all_ = 2, K.Meter(trace=[]), K.Meter(trace=[])
        while run <= m:
            gap = run // 2
            while gap:
                K.exchange(a, m, run, gap, one, ascending)
                gap //= 2
            run *= 2
        K.bitonic_sort_block(b, m, all_, ascending)
        assert (a.words == b.words).all() and (a.real == b.real).all() and (a.rec == b.rec).all() and one == all_
