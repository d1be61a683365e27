"""Random bin routing across tasks and the permutation that comes of it."""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..functions import kernels as K
from ..functions.codec import Codec
from ..plans.params import RouterParams, from_length, power_of_two
from ..plans.shared import discard, fixed_rows, materialise, ship_package

#: How a Python worker names the two errors that fresh coins mend.
_UNLUCKY = re.compile(rf"^{re.escape(K.__name__)}\.(BinOverflow|TagCollision)\b", re.M)
#: Purposes that coins are drawn for.
LABEL, TAG = 1, 2
#: Slots of a task (records and fillers), and records that a task routes at a time: public numbers, so that no task holds more, whatever the length.
TASK_SLOTS, CHUNK = 1 << 18, 1 << 16


@dataclass
class Permuted:
    """A secretly permuted table; it may feed one comparison sort. ``df`` has the columns, ``_task`` and ``_at`` (the order of the permutation)."""

    df: DataFrame
    n: int
    consumed: bool = False

    def take(self) -> DataFrame:
        if self.consumed:
            raise ValueError("a permutation feeds one sort; draw another")
        self.consumed = True
        return self.df


def _pack(s: K.Slab, z: int) -> list[bytes]:
    """Each bin as one block of the same number of bytes."""
    flat = np.concatenate((s.real.astype(np.uint8)[:, None], s.words.view(np.uint8).reshape(len(s), -1), s.rec), axis=1)
    return [b.tobytes() for b in flat.reshape(len(s) // z, -1)]


def _unpack(blocks: list[bytes], words: int, width: int) -> K.Slab:
    flat = np.frombuffer(b"".join(blocks), np.uint8).reshape(-1, 1 + 8 * words + width)
    return K.Slab(np.ascontiguousarray(flat[:, 1 : 1 + 8 * words]).view(np.uint64), flat[:, 0] == 1, flat[:, 1 + 8 * words :].copy())


def _fill(s: K.Slab, bins: int, z: int) -> K.Slab:
    """More filler bins, up to ``bins``."""
    return K.join([s, K.filler(bins * z - len(s), s)]) if len(s) < bins * z else s


def _light(s: K.Slab, level: str) -> K.Slab:
    """At the cluster level, where a task's own moves aren't hidden, places stand for records until the last move."""
    return s if level == "memory" else K.Slab(s.words, s.real, np.arange(len(s), dtype=np.int64).view(np.uint8).reshape(-1, 8))


def _heavy(s: K.Slab, rec: np.ndarray, level: str) -> K.Slab:
    """The records that the places stand for; fillers stay zero."""
    if level == "memory":
        return s
    out = np.zeros((len(s), rec.shape[1]), np.uint8)
    out[s.real] = rec[s.rec[s.real].view(np.int64).ravel()]
    return K.Slab(s.words, s.real, out)


def spread(s: K.Slab, bins: int, z: int, blocks: int = 1) -> K.Slab:
    """Real records dealt evenly to ``bins`` bins, each filled up to ``z`` slots; so many ``blocks`` side by side."""
    out = K.filler(blocks * bins * z, s)
    i = np.arange(len(s) // blocks)
    at = (np.arange(blocks)[:, None] * bins * z + (i % bins) * z + i // bins).ravel()
    out.words[at], out.real[at], out.rec[at] = s.words, s.real, s.rec
    return out


def routed(
    df: DataFrame, p: RouterParams, codec: Codec, digits: tuple[int, ...], key: bytes, level: str, form: str, label_col: str | None = None
) -> DataFrame:
    """(dest, block): blocks of ``z`` slots that one exchange a digit has brought to task ``dest``.

    Inside a task records pass the butterfly to as many bins as its input needs; the leading bits of a bin say where it goes.
    Words of a slab: draw number, label.
    """
    columns = list(codec.sizes)
    route = K.route_recursive if form == "recursive" else K.route_layered

    def send(s: K.Slab, rec: np.ndarray, bins: int, bits_of: np.ndarray, ways: int, base: int, step: int, add: int):
        s = route(s, bits_of, bins.bit_length() - 1, p.radix_bits, p.z, level)
        per = bins // ways
        dest = [base + (i // per) * step + add for i in range(bins)]
        piece = max(1, CHUNK // p.z)
        for i in range(0, bins, piece):
            blocks = _pack(_heavy(s.take(slice(i * p.z, (i + piece) * p.z)), rec, level), p.z)
            yield pa.record_batch([pa.array(dest[i : i + piece], pa.int32()), pa.array(blocks, pa.binary())], names=["dest", "block"])

    tasks = int(np.prod(digits))

    def towards(label: np.ndarray, skip: int, ways: int, bins: int) -> np.ndarray:
        """The bin of a task's own butterfly: the label's next digit says which part of them, other coins where in it.

        Digits that later tasks route by must not be used up here: their bins would arrive sorted by them.
        """
        digit, extra = ways.bit_length() - 1, bins.bit_length() - ways.bit_length()
        out = ((label << np.uint64(skip)) >> np.uint64(64 - digit)).astype(np.int64) if digit else np.zeros(len(label), np.int64)
        return out << extra | ((K.mix64(label, 11 + skip) >> np.uint64(64 - extra)).astype(np.int64) if extra else 0)

    chunk = max(CHUNK, digits[0] * p.z // 2)  # as many records as fill a bin for every task

    def first(batches):
        me, drawn, held, n, turn = TaskContext.get().partitionId(), 0, [], 0, 0

        def flush(batch: list):
            nonlocal drawn, turn
            rec = np.concatenate([codec.encode(b.select(columns)) for b in batch]) if batch else np.zeros((0, codec.width), np.uint8)
            draw = (np.uint64(me) << np.uint64(36)) + np.arange(drawn, drawn + len(rec), dtype=np.uint64)
            drawn += len(rec)
            label = K.coins(draw, 1, key, LABEL)[:, 0]
            if label_col:
                given = [b.column(b.schema.get_field_index(label_col)).to_numpy(zero_copy_only=False).astype(np.uint64) for b in batch]
                label = (np.concatenate(given or [np.zeros(0, np.uint64)]) << np.uint64(64 - p.bits)) | (label >> np.uint64(p.bits))
            s = K.Slab(np.stack((draw, label), axis=1), np.ones(len(rec), bool), rec)
            bins = max(digits[0], power_of_two(2 * max(1, len(rec)) / p.z))
            s = spread(_light(s, level), bins, p.z)
            rest = tasks // digits[0]
            # chunks take turns among the tasks that later phases tell apart, or few long inputs would fill few of them
            yield from send(s, rec, bins, towards(s.words[:, 1], 0, digits[0], bins), digits[0], 0, rest, (me + turn) % rest)
            turn += 1

        for b in batches:
            while n + b.num_rows > chunk:
                part = b.slice(0, chunk - n)
                yield from flush([*held, part])
                held, n, b = [], 0, b.slice(len(part))
            if b.num_rows:
                held.append(b)
                n += b.num_rows
        if held or not drawn:
            yield from flush(held)

    ship_package(df.sparkSession)
    out = df.mapInArrow(first, "dest int, block binary").repartitionById(tasks, F.col("dest"))
    skip = digits[0].bit_length() - 1
    for i in range(1, len(digits)):

        def again(batches, i=i, skip=skip, most=max(digits[i], 2 * CHUNK // p.z)):
            me, rest = TaskContext.get().partitionId(), int(np.prod(digits[i:]))
            below = rest // digits[i]

            def flush(blocks: list, turn: int):
                bins = max(digits[i], power_of_two(max(1, len(blocks))))
                s = _fill(_unpack(blocks, 2, codec.width), bins, p.z)
                yield from send(_light(s, level), s.rec, bins, towards(s.words[:, 1], skip, digits[i], bins), digits[i], me // rest * rest, below, (me + turn) % below)

            held, turn = [], 0
            for b in batches:
                for x in b.column(1):
                    held.append(x.as_py())
                    if len(held) == most:
                        yield from flush(held, turn)
                        held, turn = [], turn + 1
            if held or not turn:
                yield from flush(held, turn)

        out = out.mapInArrow(again, "dest int, block binary").repartitionById(tasks, F.col("dest"))
        skip += digits[i].bit_length() - 1
    return out


def task_digits(df: DataFrame, p: RouterParams, tasks: int | None, phases: int) -> tuple[int, ...]:
    """Radices of the exchanges: their product is a power of two of tasks, none with less than a bin or, unless ``tasks`` says so, more than ``TASK_SLOTS``.

    There are more phases than asked for where a bin for every task of a phase would be more than four times as much.
    """
    want = tasks or max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), 2 * p.n // TASK_SLOTS)
    total = min(power_of_two(want), max(1, p.beta))
    bits = total.bit_length() - 1
    phases = max(1, min(phases, max(bits, 1)))
    while phases < bits and (p.z << -(-bits // phases)) > 4 * TASK_SLOTS:
        phases += 1
    return tuple(1 << (bits // phases + (i < bits % phases)) for i in range(phases))


def permute(
    df: DataFrame, seed: int | None = None, widths: dict[str, int] | None = None, level: str = "memory", form: str = "recursive", gamma: int | None = None,
    tasks: int | None = None, phases: int = 1, eps: float | None = None, attempts: int = 3,
) -> Permuted:
    """A secret uniformly random permutation of the rows.

    Every row draws a bin; padded bins of fixed size pass a butterfly, of which ``phases`` transpositions are exchanges between
    tasks by public task number; each bin is then sorted by fresh tags, fillers are dropped and bins follow each other. Loads of bins become
    public, which tells nothing about the order. Coins are a keyed hash of row numbers; the key is the operating system's, or comes of ``seed`` for reproducible
    runs. The driver draws it once an attempt, and rows that reach here through an exchange are written down first, so that tasks that run again after
    the loss of an executor draw the same coins for the same rows. ``level`` says whether kernels hide accesses inside a task (``memory``) or only what leaves it (``cluster``).
    A bin that overflows, or a tag drawn twice, makes the attempt start over with other coins.
    """
    given, df = df, fixed_rows(df)
    n = df.count()
    p = from_length(n, gamma=gamma, eps=eps)
    codec = Codec(StructType([f for f in df.schema.fields]), widths or {})
    digits = task_digits(df, p, tasks, phases)
    bits_used = sum(d.bit_length() - 1 for d in digits)
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)
    route = K.route_recursive if form == "recursive" else K.route_layered
    for attempt in range(attempts):
        now = K.coin_key(None if seed is None else seed + 1_000_003 * attempt)

        def finish(batches, now=now):
            me = TaskContext.get().partitionId()
            blocks = [x for b in batches for x in b.column(1).to_pylist()]
            if not blocks:
                return
            bins = power_of_two(len(blocks))
            s = _fill(_unpack(blocks, 2, codec.width), bins, p.z)
            del blocks
            bits = bins.bit_length() - 1
            own = ((s.words[:, 1] << np.uint64(bits_used)) >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(s), np.int64)
            rec = s.rec
            s = route(_light(s, level), own, bits, p.radix_bits, p.z, level)
            s = K.tag_sort(s, p.z, K.coins(s.words[:, 0], p.tag_words, now, TAG), level, K.Meter())
            s = s.take(np.flatnonzero(s.real))
            for at in range(0, len(s), 1 << 15):
                part = _heavy(s.take(slice(at, at + (1 << 15))), rec, level).rec
                cols = codec.decode(part) + [pa.array(np.full(len(part), me), pa.int32()), pa.array(np.arange(at, at + len(part)), pa.int64())]
                yield pa.record_batch(cols, names=[*codec.sizes, "_task", "_at"])

        try:
            blocks = routed(df, p, codec, digits, now, level, form)
            done = Permuted(materialise(blocks.mapInArrow(finish, f"{fields}, _task int, _at long"), "permuted"), n)
            if df is not given:
                discard(df)
            return done
        except Exception as e:  # noqa: BLE001  the kernel's error arrives inside Spark's
            if attempt + 1 == attempts or not _UNLUCKY.search(str(e)):
                raise
    raise AssertionError


def route_bins(df: DataFrame, label: str, p: RouterParams, level: str = "memory", form: str = "layered", tasks: int | None = None, widths: dict | None = None) -> DataFrame:
    """Rows with ``_bin`` and ``_slot``: each in the bin that its label (0 to beta - 1) names; fillers are left out of the result.

    The router alone, with given labels in place of coins; the final bins are those of all tasks, in order.
    """
    data = StructType([f for f in df.schema.fields if f.name != label])
    codec = Codec(data, widths or {})
    digits = task_digits(df, p, tasks, 1)
    bits_used = digits[0].bit_length() - 1
    own_bits = p.bits - bits_used
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in data)
    route = K.route_recursive if form == "recursive" else K.route_layered

    def finish(batches):
        me = TaskContext.get().partitionId()
        blocks = [x for b in batches for x in b.column(1).to_pylist()]
        if not blocks:
            return
        bins = max(1 << own_bits, power_of_two(len(blocks)))
        extra = bins.bit_length() - 1 - own_bits
        s = _fill(_unpack(blocks, 2, codec.width), bins, p.z)
        label = ((s.words[:, 1] << np.uint64(bits_used)) >> np.uint64(64 - own_bits - extra)).astype(np.int64) if own_bits + extra else np.zeros(len(s), np.int64)
        s = route(s, label, own_bits + extra, p.radix_bits, p.z, level)
        # bins beyond those asked for split one by bits of its own; they are read as one again
        at = np.flatnonzero(s.real)
        bin_of = at // p.z >> extra
        first = np.searchsorted(bin_of, bin_of)
        cols = codec.decode(s.rec[at]) + [pa.array(bin_of + (me << own_bits), pa.int64()), pa.array(np.arange(len(at)) - first, pa.int64())]
        yield pa.record_batch(cols, names=[*codec.sizes, "_bin", "_slot"])

    return materialise(routed(fixed_rows(df), p, codec, digits, K.coin_key(0), level, form, label).mapInArrow(finish, f"{fields}, _bin long, _slot long"), "bins")
