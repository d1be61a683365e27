"""Block kernels with fixed index patterns: sorting networks, bin placement, routers and scans in numpy.

``level='memory'`` moves whole records along data-independent compare-exchanges. ``level='cluster'`` does the
same work with a local sort: its blocks have the same sizes, but what happens inside a task isn't hidden.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


class BinOverflow(RuntimeError):
    """More real records than a bin holds; an event of negligible probability, after which fresh coins are drawn."""


class TagCollision(RuntimeError):
    """Two records of a bin drew the same tag."""


@dataclass
class Meter:
    """What kernels count: comparators, record moves, layers in sequence, and, where asked for, an index trace.

    ``blocks``: independent inputs of one length that pass a kernel side by side; counts are those of all, the trace is each one's.
    """

    comparators: int = 0
    moves: int = 0
    layers: int = 0
    trace: list | None = None
    blocks: int = 1

    def note(self, what: str, *shape: int) -> None:
        if self.trace is not None:
            self.trace.append((what, *shape))


@dataclass
class Slab:
    """Records side by side: sort words (rows of 64-bit words, most significant first), flags of real records, record bytes."""

    words: np.ndarray
    real: np.ndarray
    rec: np.ndarray

    def take(self, at) -> Slab:
        return Slab(self.words[at], self.real[at], self.rec[at])

    def shape(self, *lead: int) -> Slab:
        return Slab(self.words.reshape(*lead, self.words.shape[-1]), self.real.reshape(lead), self.rec.reshape(*lead, self.rec.shape[-1]))

    def __len__(self) -> int:
        return len(self.real)


def join(slabs: list[Slab]) -> Slab:
    return Slab(np.concatenate([s.words for s in slabs]), np.concatenate([s.real for s in slabs]), np.concatenate([s.rec for s in slabs]))


def filler(n: int, like: Slab) -> Slab:
    return Slab(np.zeros((n, like.words.shape[-1]), np.uint64), np.zeros(n, bool), np.zeros((n, like.rec.shape[-1]), np.uint8))


def _greater(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Lexicographic a > b over the last axis, every word looked at."""
    out = np.zeros(a.shape[:-1], bool)
    tied = np.ones(a.shape[:-1], bool)
    for i in range(a.shape[-1]):
        out |= tied & (a[..., i] > b[..., i])
        tied &= a[..., i] == b[..., i]
    return out


def exchange(s: Slab, m: int, run: int, gap: int, meter: Meter, ascending: bool = True) -> None:
    """One layer over every row of ``m`` records: partners ``gap`` apart, direction by runs of ``run`` records."""
    lead = len(s) // m
    flip = (np.arange(m // (2 * gap)) * 2 * gap // run) % 2 == 1
    if not ascending:
        flip = ~flip
    w = s.words.reshape(lead, m // (2 * gap), 2, gap, -1)
    swap = _greater(w[:, :, 0], w[:, :, 1]) ^ flip[None, :, None]
    for x in (w, s.real.reshape(lead, m // (2 * gap), 2, gap, 1), s.rec.reshape(lead, m // (2 * gap), 2, gap, -1)):
        a, b, sw = x[:, :, 0].copy(), x[:, :, 1], swap[..., None]
        x[:, :, 0] = np.where(sw, b, a)
        x[:, :, 1] = np.where(sw, a, b)
    meter.comparators += len(s) // 2
    meter.moves += len(s)
    meter.layers += 1
    meter.note("exchange", len(s) // meter.blocks, m, run, gap)


#: Words (columns times places) that a network works on at a time: what a core's cache holds.
NEAR = 1 << 17


def _layers(s: Slab, m: int, steps: list[tuple[int, int]], meter: Meter, ascending: bool, by: int | None = None) -> None:
    """The layers (run, gap) in turn over every row of ``m`` records, in place, as ``exchange`` does each of them.

    Words, flags and record bytes lie as columns of words, a few rows side by side, at their places with bits reversed: the partners of the many short
    gaps are then long stretches. They change places by masked differences. ``by``: leading words that are compared, where those are known to differ whatever the data.
    """
    turned = np.zeros(1, np.int64)
    for _ in range(m.bit_length() - 1):
        turned = np.concatenate((2 * turned, 2 * turned + 1))
    rows, words, width = len(s) // m, s.words.shape[-1], s.rec.shape[-1]
    by, packed = by or words, -(-width // 8)
    per = max(1, NEAR // ((words + packed) * m))
    for i in range(0, rows, per):
        r = min(per, rows - i)
        here = slice(i * m, (i + r) * m)
        flat = np.zeros((r * m, 8 * packed), np.uint8)
        flat[:, :width] = s.rec[here]
        cols = np.empty((words + packed, m, r), np.uint64)
        cols[:words] = s.words[here].reshape(r, m, words)[:, turned].transpose(2, 1, 0)
        cols[words:] = flat.view(np.uint64).reshape(r, m, packed)[:, turned].transpose(2, 1, 0)
        real = np.ascontiguousarray(s.real[here].reshape(r, m)[:, turned].T)
        half, bits = np.empty((2, m // 2 * r), np.uint64), np.empty(m // 2 * r, bool)
        for run, gap in steps:
            side = (gap, m // (2 * gap), r)
            x, y = cols.reshape(words + packed, gap, 2, m // (2 * gap), r), real.reshape(gap, 2, m // (2 * gap), r)
            pairs = [(x[j, :, 0], x[j, :, 1]) for j in range(words + packed)]
            swap = np.greater(*pairs[0], out=bits.reshape(side))
            if by > 1:
                tied = pairs[0][0] == pairs[0][1]
                for a, b in pairs[1:by]:
                    swap |= tied & (a > b)
                    tied &= a == b
            falling = turned[: m // (2 * gap)] // run % 2 == (1 if ascending else 0)
            swap ^= falling[None, :, None]
            mask, apart = half[0].reshape(side), half[1].reshape(side)
            np.copyto(mask, swap)
            np.negative(mask, out=mask)
            for a, b in pairs:
                np.bitwise_xor(a, b, out=apart)
                apart &= mask
                a ^= apart
                b ^= apart
            a, b = y[:, 0], y[:, 1]
            swap &= a ^ b
            a ^= swap
            b ^= swap
        s.words[here] = cols[:words, turned].transpose(2, 1, 0).reshape(r * m, words)
        s.rec[here] = np.ascontiguousarray(cols[words:, turned].transpose(2, 1, 0)).reshape(r * m, packed).view(np.uint8)[:, :width]
        s.real[here] = real[turned].T.ravel()
    for run, gap in steps:
        meter.comparators += len(s) // 2
        meter.moves += len(s)
        meter.layers += 1
        meter.note("exchange", len(s) // meter.blocks, m, run, gap)


def _gaps(run: int) -> list[tuple[int, int]]:
    """The layers that merge runs of ``run`` records."""
    return [(run, run >> i) for i in range(1, run.bit_length())]


def bitonic_merge_block(s: Slab, m: int, meter: Meter, ascending: bool = True, recursive: bool = False) -> None:
    """Each row of ``m`` records (rising then falling, or the reverse) becomes sorted, in place.

    ``recursive``: the first half of the layers as sorts of the columns of a matrix, then the rest as
    sorts of its rows; the same comparators, in an order that keeps to small pieces of memory.
    """
    if m < 2:
        return
    if recursive and m > 4:
        k = m.bit_length() - 1
        rows, cols = 1 << -(-k // 2), 1 << k // 2
        lead = len(s) // m
        turn = lambda x, a, b: np.ascontiguousarray(x.reshape(lead, a, b, *x.shape[1:]).swapaxes(1, 2)).reshape(x.shape)
        t = Slab(turn(s.words, rows, cols), turn(s.real, rows, cols), turn(s.rec, rows, cols))
        before = meter.layers
        bitonic_merge_block(t, rows, meter, ascending, True)
        s.words[:], s.real[:], s.rec[:] = turn(t.words, cols, rows), turn(t.real, cols, rows), turn(t.rec, cols, rows)
        bitonic_merge_block(s, cols, meter, ascending, True)
        meter.layers = before + k
        meter.note("transpose", rows, cols)
        return
    _layers(s, m, _gaps(m), meter, ascending)


def bitonic_sort_block(s: Slab, m: int, meter: Meter | None = None, ascending: bool = True, recursive: bool = False, by: int | None = None) -> Slab:
    """Every row of ``m`` (a power of two) records sorted by their words, in place; ``by``: as many words suffice, for they differ whatever the data."""
    meter = meter or Meter()
    run = 2
    if not recursive:
        _layers(s, m, [step for k in range(1, m.bit_length()) for step in _gaps(1 << k)], meter, ascending, by)
        return s
    while run <= m:
        if run > 4:
            # rows of ``run``: odd ones fall
            rows = len(s) // run
            falling = (np.arange(rows) % 2 == 1) & (run < m)
            for down in (False, True):
                pick = np.flatnonzero(falling == down)
                if not len(pick):
                    continue
                part = s.shape(rows, run).take(pick).shape(len(pick) * run)
                layers = meter.layers
                bitonic_merge_block(part, run, meter, ascending != down, True)
                if down:
                    meter.layers = layers
                whole = s.shape(rows, run)
                whole.words[pick], whole.real[pick], whole.rec[pick] = (x.reshape(len(pick), run, *x.shape[1:]) for x in (part.words, part.real, part.rec))
        else:
            _layers(s, m, _gaps(run), meter, ascending)
        run *= 2
    return s


def comparators(n: int) -> int:
    """Comparators of a bitonic sort of n = 2 ** k records: n k (k + 1) / 4."""
    k = n.bit_length() - 1
    return n * k * (k + 1) // 4


def _row_sort(s: Slab, m: int, level: str, meter: Meter) -> Slab:
    if level == "memory":
        return bitonic_sort_block(s, m, meter)
    row = np.arange(len(s)) // m
    return s.take(np.lexsort((*s.words.T[::-1], row)))


def place_block(s: Slab, groups: int, bins: int, z: int, dest: np.ndarray, level: str, meter: Meter) -> Slab:
    """In each group of ``bins`` bins of ``z`` slots, real records move to the bin that ``dest`` names; reals first, exactly ``z`` slots.

    The network form: as many temporary fillers as slots, one sort by (bin, real before temporary), ranks within bins
    by a scan, a second sort by (left out, bin, rank), and a cut to the slots.
    """
    m = bins * z
    meter.note("place", groups // meter.blocks, bins, z)
    if level == "cluster":
        g = np.arange(len(s)) // m
        where = np.flatnonzero(s.real)
        target = g[where] * bins + dest[where]
        order = np.argsort(target, kind="stable")
        where, target = where[order], target[order]
        load = np.bincount(target, minlength=groups * bins)
        if load.max(initial=0) > z:
            raise BinOverflow(f"{load.max()} records for a bin of {z}")
        first = np.cumsum(load) - load
        slot = target * z + np.arange(len(where)) - first[target]
        out = filler(len(s), s)
        out.words[slot], out.real[slot], out.rec[slot] = s.words[where], True, s.rec[where]
        return out
    width = s.words.shape[1]
    both = Slab(
        np.zeros((groups, 2 * m, width + 1), np.uint64), np.zeros((groups, 2 * m), bool), np.zeros((groups, 2 * m, s.rec.shape[1]), np.uint8)
    )
    both.words[:, :m, 1:], both.real[:, :m], both.rec[:, :m] = s.words.reshape(groups, m, -1), s.real.reshape(groups, m), s.rec.reshape(groups, m, -1)
    # first sort: word 0 holds bin, kind (real 0, temporary 1) and place; fillers of the input come last
    place = np.arange(2 * m, dtype=np.uint64)
    bin_of = np.where(s.real, dest, bins).reshape(groups, m).astype(np.uint64)
    both.words[:, :m, 0] = (bin_of << np.uint64(33)) | place[:m]
    both.words[:, m:, 0] = (np.repeat(np.arange(bins, dtype=np.uint64), z) << np.uint64(33)) | np.uint64(1 << 32) | place[m:]
    flat = both.shape(groups * 2 * m)
    bitonic_sort_block(flat, 2 * m, meter, by=1)  # the place makes the first word distinct
    b = (flat.words[:, 0] >> np.uint64(33)).astype(np.int64).reshape(groups, 2 * m)
    here = np.broadcast_to(np.arange(2 * m), b.shape)
    start = np.maximum.accumulate(np.where(np.diff(b, axis=1, prepend=-1) != 0, here, 0), axis=1)
    rank = here - start
    lost = (rank >= z) & flat.real.reshape(b.shape)
    out_of = (rank >= z) | (b >= bins)
    flat.words[:, 0] = ((out_of.astype(np.uint64) << np.uint64(63)) | (b.astype(np.uint64) << np.uint64(32)) | rank.astype(np.uint64)).ravel()
    bitonic_sort_block(flat, 2 * m, meter, by=1)  # and so does the rank within a bin
    if lost.any():  # only after the fixed course has run to its end
        raise BinOverflow(f"a bin of {z} overflows")
    kept = flat.shape(groups, 2 * m)
    return Slab(kept.words[:, :m, 1:].reshape(-1, width), kept.real[:, :m].reshape(-1), kept.rec[:, :m].reshape(len(s), -1))


def digits_of(bits: int, radix_bits: int) -> list[int]:
    """Bits per layer, most significant first; the last layer takes what is left."""
    return [min(radix_bits, bits - i) for i in range(0, bits, radix_bits)]


def route_layered(s: Slab, label: np.ndarray, bits: int, radix_bits: int, z: int, level: str = "cluster", meter: Meter | None = None) -> Slab:
    """Bins of ``z`` slots, 2 ** ``bits`` of them, through layers of ``radix_bits``: bin i of the result holds the records with label i.

    The label travels as the last sort word. ``meter.blocks`` inputs may stand side by side.
    """
    meter, beta = meter or Meter(), 1 << bits
    each = np.arange(meter.blocks)[:, None] * beta
    s = Slab(np.concatenate((s.words, label.astype(np.uint64)[:, None]), axis=1), s.real, s.rec)
    done = 0
    for d in digits_of(bits, radix_bits):
        high, ways, low = 1 << done, 1 << d, beta >> (done + d)
        perm = np.arange(beta).reshape(high, ways, low).swapaxes(1, 2).ravel()  # bins that agree in all digits but this one, side by side
        g = s.shape(len(s) // z, z).take((each + perm).ravel()).shape(len(s))
        dest = (g.words[:, -1].astype(np.int64) >> (bits - done - d)) & (ways - 1)
        g = place_block(g, meter.blocks * high * low, ways, z, dest, level, meter)
        back = np.argsort(perm)
        s = g.shape(len(s) // z, z).take((each + back).ravel()).shape(len(s))
        done += d
    return Slab(s.words[:, :-1], s.real, s.rec)


def route_recursive(s: Slab, label: np.ndarray, bits: int, radix_bits: int, z: int, level: str = "cluster", meter: Meter | None = None) -> Slab:
    """The same by halving the label: rows of bins by the leading bits, a transposition, then rows by the other bits."""
    meter = meter or Meter()
    r = meter.blocks
    s = Slab(np.concatenate((s.words, label.astype(np.uint64)[:, None]), axis=1), s.real, s.rec)
    one = lambda whole, j: Slab(*(np.ascontiguousarray(x[:, j]) for x in (whole.words, whole.real, whole.rec)))  # noqa: E731  row j of each input

    def solve(part: Slab, bits_left: int, low_bit: int) -> Slab:
        beta = 1 << bits_left
        if bits_left <= radix_bits:
            dest = (part.words[:, -1].astype(np.int64) >> low_bit) & (beta - 1)
            return place_block(part, r, beta, z, dest, level, meter)
        first = bits_left // 2  # bins in a partition; where the bits are odd there are more partitions
        second = bits_left - first
        rows, cols = 1 << second, 1 << first
        whole = part.shape(r, rows, cols * z)
        done = [solve(one(whole, j).shape(r * cols * z), first, low_bit + second) for j in range(rows)]
        meter.note("transpose", rows, cols)
        t = join(done).shape(rows, r, cols, z)
        t = Slab(*(np.moveaxis(x, 0, 2) for x in (t.words, t.real, t.rec)))  # inputs, columns, rows, slots
        done = [solve(one(t, i).shape(r * rows * z), second, low_bit) for i in range(cols)]
        if r == 1:
            return join(done)
        t = join(done).shape(cols, r, rows * z)
        return Slab(*(np.ascontiguousarray(x.swapaxes(0, 1)) for x in (t.words, t.real, t.rec))).shape(r * cols * rows * z)

    out = solve(s, bits, 0)
    return Slab(out.words[:, :-1], out.real, out.rec)


def tag_sort(s: Slab, z: int, tags: np.ndarray, level: str, meter: Meter) -> Slab:
    """Each bin of ``z`` slots in order of its tags, fillers last."""
    words = np.concatenate(((~s.real).astype(np.uint64)[:, None], tags, np.arange(len(s), dtype=np.uint64)[:, None] % np.uint64(z)), axis=1)
    t = _row_sort(Slab(words, s.real.copy(), s.rec.copy()), z, level, meter)
    same = (t.words[1:, 1:-1] == t.words[:-1, 1:-1]).all(1) & t.real[1:] & t.real[:-1] & (np.arange(1, len(t)) % z != 0)
    if same.any():
        raise TagCollision("equal tags in a bin")
    return t


def mix64(x: np.ndarray, salt: int) -> np.ndarray:
    """Salted 64-bit mix of numbers that are random already."""
    with np.errstate(over="ignore"):
        z = x.astype(np.uint64) + np.uint64((salt * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(31))


def _rotate(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def keyed_hash(key: bytes, first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """SipHash-2-4 of 16-byte messages (two little-endian words each) under a 16-byte key: a pseudorandom function, in whole arrays."""
    k0, k1 = (np.uint64(x) for x in np.frombuffer(key, "<u8"))
    start = (0x736F6D6570736575, 0x646F72616E646F6D, 0x6C7967656E657261, 0x7465646279746573)  # fixed values of the function
    v = [np.full(len(first), np.uint64(c) ^ k, np.uint64) for c, k in zip(start, (k0, k1, k0, k1))]

    def mix(rounds: int) -> None:
        for _ in range(rounds):
            for a, b, far in ((0, 1, 13), (2, 3, 16)):
                v[a] += v[b]
                v[b] = _rotate(v[b], far) ^ v[a]
            v[0] = _rotate(v[0], 32)
            for a, b, far in ((0, 3, 21), (2, 1, 17)):
                v[a] += v[b]
                v[b] = _rotate(v[b], far) ^ v[a]
            v[2] = _rotate(v[2], 32)

    with np.errstate(over="ignore"):
        for word in (first, second, np.uint64(16 << 56)):
            v[3] ^= word
            mix(2)
            v[0] ^= word
        v[2] ^= np.uint64(0xFF)
        mix(4)
        return v[0] ^ v[1] ^ v[2] ^ v[3]


def coin_key(seed: int | bytes | None) -> bytes:
    """The 16-byte key of an attempt's coins: the operating system's without a seed. It is drawn once, on the driver, so that a task that runs again draws what it drew before."""
    import hashlib
    import os

    if isinstance(seed, bytes):
        return seed
    return os.urandom(16) if seed is None else hashlib.blake2b(str(seed).encode(), digest_size=16).digest()


def coins(draw: np.ndarray, words: int, seed: int | bytes | None, purpose: int) -> np.ndarray:
    """``words`` random 64-bit words for each draw number, by the keyed hash of number, purpose and word."""
    key, draw = coin_key(seed), np.asarray(draw, np.uint64)
    if not words:
        return np.zeros((len(draw), 0), np.uint64)
    return np.stack([keyed_hash(key, draw, np.full(len(draw), (purpose << 32) + i, np.uint64)) for i in range(words)], axis=1)
