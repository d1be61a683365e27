"""What a task of the passage search holds."""

import tracemalloc

import numpy as np

from oblivspark.llm import suffix_dedup as S

LENGTH = 100


def test_slices_are_even():
    """Anchors have the least hashes of their windows; their slices are as full as each other all the same."""
    text = np.random.default_rng(1).integers(97, 123, 1 << 20, np.uint8).tobytes()
    h = S.anchors(text, LENGTH)[1]
    full = np.bincount(S.slices_of(h, S.slice_bits(0, LENGTH)), minlength=64)
    assert full.sum() > 20_000 and full.max() < 2 * full.mean() and full.min() > full.mean() / 2


def test_sample_by_places():
    """Each place is as likely to be taken, wherever a task's batches are cut."""
    whole = S.picked(0, 100_000, 50)
    parts = np.concatenate([S.picked(a, 1000, 50) + a for a in range(0, 100_000, 1000)])
    assert (whole == parts).all() and 1700 < len(whole) < 2300
    assert len(S.picked(5, 70, 1)) == 70


def test_bucket_in_few_bytes_a_suffix():
    """A lead that very many documents continue in their own ways: what its bucket needs doesn't grow with the windows of a suffix."""
    r = np.random.default_rng(2)
    n, span = 20_000, LENGTH - S.LEAD
    common = r.integers(97, 123, 2 * LENGTH - S.LEAD, np.uint8)  # all windows of a full run are equal; each tenth has another end
    rows = np.tile(common, (n, 1))
    rows[::10, -20:] = r.integers(97, 123, (n // 10, 20), np.uint8)
    flat, offsets = rows.reshape(-1), np.arange(n + 1) * rows.shape[1]
    doc, zero = np.arange(n), np.zeros(n, np.int64)
    tracemalloc.start()
    row, lo, hi = S.later_windows(doc, zero, zero + span, zero, zero + span, flat, offsets, LENGTH)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 500 * n
    seen, want = set(), set()
    for i, text in enumerate(x.tobytes() for x in rows):
        for at in range(span + 1):
            window = text[at : at + LENGTH]
            if window in seen:
                want.add((i, at))
            seen.add(window)
    assert {(int(i), at) for i, a, b in zip(row, lo, hi) for at in range(a, b + 1)} == want
    assert len(row) < 1.01 * n  # runs, not windows
