"""Repeated passages by a sparse suffix array: sampled splitters, range buckets, multikey sorting."""

from __future__ import annotations

import hashlib
import uuid

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.shared import materialise
from .base import column, id_and_text, map_batches, texts_of

#: Bytes of the shingle at which a suffix may begin, a power of two.
LEAD = 32
#: Least number of slices of the shingle hashes, and hashes that a slice aims at; hashes that are broadcast at a time; least number of leads that splitters are picked from.
SLICES, SLICE_HASHES, ROUND_HASHES, SPLITTER_SAMPLE = 64, 1 << 23, 1 << 23, 1 << 16
#: Bytes of suffixes per bucket that the splitters aim at, and the least number of buckets.
BUCKET_BYTES, BUCKETS = 2 << 20, 96
#: Shingle hashes, and suffixes, that a task holds before it hands them on.
HELD, HELD_SUFFIXES = 1 << 21, 1 << 16
_RNG = np.random.default_rng(7)
#: A random 64-bit number for each byte, and an odd one for each doubling.
_BYTE = _RNG.integers(0, 1 << 63, 256, np.uint64) * np.uint64(2) + np.uint64(1)
_STEP = _RNG.integers(0, 1 << 63, 8, np.uint64) * np.uint64(2) + np.uint64(1)
#: An odd number: anchors have small hashes, and times this the leading bits of those are spread evenly again.
_SPREAD = np.uint64(0xD6E8FEB86659FD93)


def shingle_hashes(b: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the ``LEAD`` bytes from each place on, by doubling."""
    h, width, i = _BYTE[b], 1, 0
    with np.errstate(over="ignore"):
        while width < LEAD:
            h = h[:-width] * _STEP[i] + h[width:]
            h ^= h >> np.uint64(29)
            width, i = 2 * width, i + 1
        h *= np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(32)
    return h


def anchors(text: bytes, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray] | None:
    """Places where suffixes begin: (place, spread-out hash, first window, last window).

    Each window of ``length`` bytes picks its leftmost shingle of least hash, so equal windows pick the same
    place in themselves; a place stands for the run of windows that pick it. Needs about 2 / (length - LEAD) of all places.
    """
    if len(text) < length:
        return None
    h = shingle_hashes(np.frombuffer(text, np.uint8))
    span, width = length - LEAD + 1, 1
    low = (h >> np.uint64(32) << np.uint64(32)) | np.arange(len(h), dtype=np.uint64)
    while 2 * width <= span:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    if width < span:
        low = np.minimum(low[: len(h) - span + 1], low[span - width : span - width + len(h) - span + 1])
    at = (low & np.uint64(0xFFFFFFFF)).astype(np.int64)
    cut = np.flatnonzero(np.diff(at)) + 1
    first = np.concatenate(([0], cut))
    place = at[first]
    with np.errstate(over="ignore"):
        return place, h[place] * _SPREAD, first, np.append(cut, len(at)) - 1


def slice_bits(volume: int, length: int) -> int:
    """The leading bits of a hash that name its slice: as many slices as keep each within reach of one task, whatever the volume."""
    hashes = 2 * volume // (length - LEAD)
    return (max(SLICES, -(-hashes // SLICE_HASHES)) - 1).bit_length()


def slices_of(h: np.ndarray, bits: int) -> np.ndarray:
    return (h >> np.uint64(64 - bits)).astype(np.int64)


def picked(seen: int, n: int, sample_of: int) -> np.ndarray:
    """Which of the next ``n`` places go into the sample, one in ``sample_of``: by the place's number in its task, so that a lead is in it as often as it weighs."""
    with np.errstate(over="ignore"):
        x = np.arange(seen, seen + n, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(32))) * _SPREAD
        return np.flatnonzero((x ^ (x >> np.uint64(32))) % np.uint64(sample_of) == 0)


def repeated_slices(base: DataFrame, length: int, sample_of: int, bits: int) -> DataFrame:
    """(slice, hashes, leads): shingle hashes that occur twice or more, and a sample of their first bytes, each place as likely as any other."""

    def gather(batches):
        held, leads, n, seen = [], [], 0, 0

        def flush():
            if not held:
                return
            k, c = np.unique(np.concatenate(held), return_counts=True)
            slot = slices_of(k, bits)
            cut = np.append(np.flatnonzero(np.diff(slot, prepend=-1)), len(slot))
            mine = sorted(leads)
            of = np.array([x[0] for x in mine], np.uint64)
            for a, b in zip(cut, cut[1:]):
                near = mine[np.searchsorted(of, k[a]) : np.searchsorted(of, k[b - 1], "right")] if len(of) else []
                yield pa.record_batch(
                    [pa.array([slot[a]], pa.int32()), pa.array([k[a:b].tobytes()], pa.binary()), pa.array([np.packbits(c[a:b] > 1).tobytes()], pa.binary()), pa.array([[x[0].to_bytes(8, "little") + x[1] for x in near]], pa.list_(pa.binary()))],
                    names=["slice", "hashes", "twice", "leads"],
                )
            held.clear()
            leads.clear()

        for batch in batches:
            for text in texts_of(batch):
                found = anchors(text, length)
                if found is None:
                    continue
                place, h = found[:2]
                held.append(h)
                n += len(h)
                for i in picked(seen, len(h), sample_of):
                    leads.append((int(h[i]), text[place[i] : place[i] + LEAD]))
                seen += len(h)
            if n >= HELD:
                yield from flush()
                n = 0
        yield from flush()

    def merge(table: pa.Table) -> pa.Table:
        parts = [np.frombuffer(b.as_buffer(), np.uint64) for b in table["hashes"]]
        twice = [p[np.unpackbits(np.frombuffer(b.as_buffer(), np.uint8), count=len(p)) == 1] for p, b in zip(parts, table["twice"])]
        k = np.concatenate(parts)
        k.sort()
        k = np.unique(np.concatenate((k[1:][k[1:] == k[:-1]], *twice)))
        leads = [x for xs in table["leads"].to_pylist() for x in xs]
        of = np.array([int.from_bytes(x[:8], "little") for x in leads], np.uint64)
        leads = [x[8:] for x, keep in zip(leads, np.isin(of, k)) if keep]
        return pa.table({"size": pa.array([len(k)], pa.int64()), "slice": pa.array([table["slice"][0].as_py()], pa.int32()), "hashes": pa.array([k.tobytes()], pa.binary()), "leads": pa.array([leads], pa.list_(pa.binary()))})

    rows = map_batches(base.select("text"), gather, "slice int, hashes binary, twice binary, leads array<binary>")
    return rows.groupBy("slice").applyInArrow(merge, "size long, slice int, hashes binary, leads array<binary>")


def candidates(text: bytes, length: int, repeated: np.ndarray, rounds: tuple[int, int], bits: int):
    """(place, first window, last window) of the suffixes whose shingle repeats and belongs to the round."""
    found = anchors(text, length)
    if found is None:
        return
    place, h, first, last = found
    i = np.minimum(np.searchsorted(repeated, h), max(len(repeated) - 1, 0))
    again = repeated[i] == h if len(repeated) else np.zeros(len(h), bool)
    slot = slices_of(h, bits)
    for j in np.flatnonzero(again & (slot >= rounds[0]) & (slot < rounds[1])):
        yield int(place[j]), int(first[j]), int(last[j])


def multikey_order(words: np.ndarray) -> np.ndarray:
    """Order of rows of big-endian 64-bit tokens: three-way partition on one token after the other.

    Rows with equal tokens so far go on to the next token together; short runs are sorted at once.
    """
    order = np.arange(len(words))
    todo = [(0, len(words), 0)]
    while todo:
        a, b, d = todo.pop()
        if b - a < 2 or d == words.shape[1]:
            continue
        rows = order[a:b]
        if b - a <= 4096:
            order[a:b] = rows[np.lexsort(words[rows, d:].T[::-1])]
            continue
        token = words[rows, d]
        pivot = np.sort(token[:: max(1, len(token) // 31)])
        pivot = pivot[len(pivot) // 2]
        less, same = token < pivot, token == pivot
        order[a:b] = np.concatenate((rows[less], rows[same], rows[token > pivot]))
        i, j = a + int(less.sum()), a + int(less.sum() + same.sum())
        todo += [(a, i, d), (i, j, d + 1), (j, b, d)]
    return order


def shared_bytes(words: np.ndarray, order: np.ndarray) -> np.ndarray:
    """Bytes that each row of the order shares with the one before (0 for the first)."""
    out = np.zeros(len(order), np.int64)
    if len(order) < 2:
        return out
    x = words[order[1:]] ^ words[order[:-1]]
    full = np.argmax(x != 0, axis=1)
    none = ~(x != 0).any(1)
    word = x[np.arange(len(x)), full]
    lead = np.zeros(len(x), np.int64)  # equal bytes at the front of the first unequal token
    for byte in range(1, 8):
        lead += (word >> np.uint64(64 - 8 * byte)) == 0
    out[1:] = np.where(none, 8 * words.shape[1], 8 * full + lead)
    return out


def flat_tokens(flat: np.ndarray, at: np.ndarray, end: np.ndarray, width: int) -> np.ndarray:
    """``width`` bytes from each place of a flat array on, as rows of big-endian 64-bit tokens; beyond ``end`` zero bytes."""
    out = np.zeros((len(at), -(-width // 8) * 8), np.uint8)
    for j in range(width):
        on = np.flatnonzero(at + j < end)
        out[on, j] = flat[at[on] + j]
    return out.view(">u8").byteswap(inplace=True).view(np.uint64)


def as_tokens(parts: list[bytes], width: int) -> np.ndarray:
    """Each part, filled up with zero bytes, as a row of big-endian 64-bit tokens."""
    end = np.cumsum([len(p) for p in parts])
    return flat_tokens(np.frombuffer(b"".join(parts), np.uint8), end - [len(p) for p in parts], end, width)


def later_windows(doc: np.ndarray, tie: np.ndarray, place: np.ndarray, first: np.ndarray, last: np.ndarray, flat: np.ndarray, offsets: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, lo, hi): runs of window starts that earlier equal windows precede in the bucket.

    ``flat`` and ``offsets``: each row's text from its first window to the end of its last. The suffixes from each place on are sorted;
    a window that begins ``back`` bytes before its place is equal to another where the suffixes share ``length - back`` bytes and the texts
    share the ``back`` bytes before. What is held is a few hundred bytes a row, however many windows a row has.
    """
    n = len(doc)
    at = offsets[:-1] + place - first
    words = flat_tokens(flat, at, np.minimum(offsets[1:], at + length), length)
    order = multikey_order(words)
    lcp = shared_bytes(words, order)
    del words
    back_most, back_least, at = (place - first)[order], (place - last)[order], at[order]
    # running hashes of the bytes before each place, from the place backwards
    run = np.zeros(n, np.uint64)
    d, t, p = doc[order], tie[order], place[order]
    low, high = np.full(n, -1), np.full(n, -1)  # each row's open run; starts come in falling order
    done: list[tuple] = []
    for back in range(int(back_most.max(initial=0)) + 1):
        if back:
            far = np.flatnonzero(back <= back_most)
            with np.errstate(over="ignore"):
                x = (run[far] ^ _BYTE[flat[at[far] - back]]) * _STEP[0]
                run[far] = x ^ (x >> np.uint64(31))
        group = np.cumsum(lcp < length - back)
        mine = np.flatnonzero((back_least <= back) & (back <= back_most))
        if len(mine) < 2:
            continue
        g, r = group[mine], run[mine]
        by = np.lexsort((p[mine], t[mine], d[mine], r, g))
        g, r, m = g[by], r[by], mine[by]
        same = (g[1:] == g[:-1]) & (r[1:] == r[:-1])
        # the first of each group of equal windows stays, and so do other rows of that very place
        head = np.concatenate(([True], ~same))
        first_of = np.maximum.accumulate(np.where(head, np.arange(len(m)), 0))
        f = m[first_of]
        m = m[(d[m] != d[f]) | (t[m] != t[f]) | (p[m] != p[f])]
        start = p[m] - back
        fresh = low[m] != start + 1
        closed = m[fresh & (high[m] >= 0)]
        done.append((closed, low[closed], high[closed]))
        high[m[fresh]] = start[fresh]
        low[m] = start
    left = np.flatnonzero(high >= 0)
    row, lo, hi = (np.concatenate(x) for x in zip(*done, (left, low[left], high[left])))
    return order[row], lo, hi


def covered(ranges: list[tuple[int, int]], length: int) -> list[tuple[int, int]]:
    """Bytes that windows with starts in the ranges cover, as maximal runs (from, to)."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(ranges):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], b + length))
        else:
            out.append((a, b + length))
    return out


_loaded: dict[str, tuple] = {}


def _key(text: bytes) -> int:
    return xxhash.xxh3_64_intdigest(text) - (1 << 63)


def _later(base: DataFrame, length: int, repeated: np.ndarray, splitters: list[bytes], rounds: tuple[int, int], bits: int) -> DataFrame:
    """(doc_id, tie, lo, hi): ranges of window starts that an earlier equal window precedes, for one round's hashes."""
    shared, name = base.sparkSession.sparkContext.broadcast((repeated, splitters)), uuid.uuid4().hex

    def emit(batches):
        if name not in _loaded:
            _loaded.clear()
            _loaded[name] = (shared.value[0], np.array(shared.value[1], dtype=f"S{LEAD}"))
        repeated, cuts = _loaded[name]
        held: dict[tuple, tuple] = {}
        known: list[tuple] = []

        def flush():
            rows = [(v[0], v[1], v[2], v[2] - k[1], v[2] - k[1] + k[2], k[0]) for k, v in held.items()]
            lead = np.array([r[5][r[2] - r[3] : r[2] - r[3] + LEAD] for r in rows], dtype=f"S{LEAD}")
            bucket = np.searchsorted(cuts, lead, "right") if len(cuts) else np.zeros(len(rows), np.int64)
            both = [(int(b), *r) for b, r in zip(bucket, rows)] + [((k[0] ^ k[2]) % (len(cuts) + 1), k[0], k[1], k[2], k[3], k[4], None) for k in known]
            if both:
                kinds = (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
                yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*both), kinds)], names=["bucket", "doc_id", "tie", "place", "first", "last", "context"])
            held.clear()
            known.clear()

        for batch in batches:
            ids = column(batch, "doc_id").to_pylist()
            for doc, text in zip(ids, texts_of(batch)):
                tie = None
                for place, first, last in candidates(text, length, repeated, rounds, bits):
                    tie = _key(text) if tie is None else tie
                    k = (text[first : last + length], place - first, last - first)
                    now = (doc, tie, place)
                    was = held.setdefault(k, now)
                    if was != now:  # the task has just this piece of text already: of the two, the later one is settled
                        if now < was:
                            held[k], was, now = now, now, was
                        known.append((now[0], now[1], now[2], now[2] - k[1], now[2] - k[1] + k[2]))
                if len(held) + len(known) >= HELD_SUFFIXES:
                    yield from flush()
        yield from flush()

    def settle(table: pa.Table) -> pa.Table:
        cols = {c: table[c].to_numpy() for c in ("doc_id", "tie", "place", "first", "last")}
        context = table["context"].combine_chunks()
        own, rest = context.is_valid().to_numpy(zero_copy_only=False), context.is_null().to_numpy(zero_copy_only=False)
        context = pa.concat_arrays([context.drop_null().cast(pa.large_binary())])
        flat, offsets = np.frombuffer(context.buffers()[2] or b"", np.uint8), np.frombuffer(context.buffers()[1], np.int64)[context.offset :][: len(context) + 1]
        row, lo, hi = later_windows(*(cols[c][own] for c in cols), flat, offsets, length)
        row = np.flatnonzero(own)[row]
        return pa.table({
            "doc_id": np.concatenate((cols["doc_id"][row], cols["doc_id"][rest])), "tie": np.concatenate((cols["tie"][row], cols["tie"][rest])),
            "lo": np.concatenate((lo, cols["first"][rest])), "hi": np.concatenate((hi, cols["last"][rest])),
        })

    dealt = map_batches(base, emit, "bucket int, doc_id long, tie long, place long, first long, last long, context binary")
    return dealt.groupBy("bucket").applyInArrow(settle, "doc_id long, tie long, lo long, hi long")


def suffix_dedup(
    docs: DataFrame, length: int = 100, id_col: str = "doc_id", text_col: str = "text", carry: bool = False, round_hashes: int = ROUND_HASHES
) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans (with ``carry`` also the kept bytes).

    Every byte goes that lies in a string of ``length`` bytes which also starts earlier: in a document of lesser id, or
    earlier in the same. Suffixes begin only at anchors, which every window picks from its own content, so that equal windows pick the
    same one; suffixes whose first ``LEAD`` bytes occur once are left out after one exchange of hashes. The rest are dealt
    to buckets by splitters sampled from those first bytes, so that all suffixes with equal leads meet; each bucket is sorted by
    multikey partition and neighbours are compared. Equal pieces within a task are settled there and travel once, so a
    passage of a third of all documents reaches its bucket once a task. The hashes of repeated leads
    are broadcast at most ``round_hashes`` at a time; with more, the suffixes are done in rounds by hash.

    Ids are cast to long; a null id comes before all others. Rows that repeat an id are ordered by a hash of their
    text; wholly equal rows are one document and fare alike. Null or short text: nothing to remove. Empty table: no rows.
    """
    if not LEAD < length < 1 << 16:
        raise ValueError(f"length is over {LEAD}")
    base = id_and_text(docs, id_col, text_col).select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("doc_id"), "text")
    volume = base.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    buckets = max(BUCKETS, volume // 4 // BUCKET_BYTES)
    sample_of = max(1, volume // (length - LEAD) * 2 // max(SPLITTER_SAMPLE, 4 * buckets))
    bits = slice_bits(volume, length)
    slices = materialise(repeated_slices(base, length, sample_of, bits), "repeated")
    sizes = {r[0]: r[1] for r in slices.select("slice", "size").collect()}
    later, at = None, 0
    while at < 1 << bits:
        end, size = at + 1, sizes.get(at, 0)
        while end < 1 << bits and size + sizes.get(end, 0) <= round_hashes:
            size += sizes.get(end, 0)
            end += 1
        rows = slices.filter(F.col("slice").between(at, end - 1)).collect()
        repeated = np.sort(np.concatenate([np.empty(0, np.uint64), *(np.frombuffer(bytes(r["hashes"]), np.uint64) for r in rows)]))
        leads = sorted(bytes(x) for r in rows for x in r["leads"])
        n = min(buckets, len(leads))
        splitters = sorted({leads[len(leads) * i // n].ljust(LEAD, b"\0") for i in range(1, n)})
        one = _later(base, length, repeated, splitters, (at, end), bits)
        later = one if later is None else later.unionByName(one)
        at = end
    ranges = later.groupBy("doc_id", "tie").agg(F.collect_list(F.struct("lo", "hi")).alias("ranges"))
    ranges = materialise(ranges, "later").select(F.col("doc_id").alias("_d"), F.col("tie").alias("_t"), "ranges")

    def tied(batches):
        for batch in batches:
            yield pa.record_batch([*batch.columns, pa.array([_key(t) for t in texts_of(batch)], pa.int64())], names=[*batch.schema.names, "tie"])

    whole = id_and_text(docs, id_col, text_col)
    kind = whole.schema["doc_id"].dataType.simpleString()
    order = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)))
    joined = map_batches(whole, tied, f"doc_id {kind}, text string, tie long").withColumn("_o", order)
    joined = joined.join(ranges, (F.col("_o") == F.col("_d")) & (F.col("tie") == F.col("_t")), "left").select("doc_id", "text", "ranges")

    def cut(batches):
        for batch in batches:
            out = {c: [] for c in ("n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", *(["kept"] if carry else []))}
            for text, own in zip(texts_of(batch), column(batch, "ranges").to_pylist()):
                spans = covered([(r["lo"], r["hi"]) for r in own], length) if own else []
                kept, at = [], 0
                for a, b in spans:
                    kept.append(text[at:a])
                    at = b
                kept = b"".join([*kept, text[at:]])
                out["n_bytes"].append(len(text))
                out["n_removed"].append(len(text) - len(kept))
                out["n_spans"].append(len(spans))
                out["kept_sha256"].append(hashlib.sha256(kept).hexdigest())
                out["spans"].append([{"start": a, "end": b} for a, b in spans])
                if carry:
                    out["kept"].append(kept)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])), pa.binary())
            yield pa.record_batch([column(batch, "doc_id"), *(pa.array(v, t) for v, t in zip(out.values(), kinds))], names=["doc_id", *out])

    return map_batches(joined, cut, f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<start:long,end:long>>" + (", kept binary" if carry else ""))
