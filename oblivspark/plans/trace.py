"""What an observer sees, as data: of kernels the index patterns, of jobs the shape and the sizes of what tasks read and write."""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame

from ..functions import kernels as K
from .params import RouterParams


def kernel_view(method: str, keys: np.ndarray, p: RouterParams | None = None, seed: int = 0) -> list[tuple]:
    """The trace of a kernel over given (secret) keys; a data-independent kernel gives the same for any keys of the same number.

    Rows of a matrix of keys are inputs of their own, which pass the kernel side by side: the trace is each one's.
    """
    blocks, n = (1, len(keys)) if keys.ndim == 1 else keys.shape
    meter, keys = K.Meter(trace=[], blocks=blocks), keys.ravel()
    s = K.Slab(keys.astype(np.uint64)[:, None].copy(), np.ones(len(keys), bool), keys.astype(np.uint64).view(np.uint8).reshape(-1, 8).copy())
    if method == "bitonic sort":
        K.bitonic_sort_block(s, n, meter)
    elif method == "bitonic sort, recursive":
        K.bitonic_sort_block(s, n, meter, recursive=True)
    elif method in ("layered router", "recursive router"):
        from ..operators.permute import spread

        full = spread(s, p.beta, p.z, blocks)
        label = np.tile((K.coins(np.arange(p.slots, dtype=np.uint64), 1, seed, 1)[:, 0] >> np.uint64(64 - p.bits)).astype(np.int64), blocks)
        route = K.route_layered if method == "layered router" else K.route_recursive
        route(full, label, p.bits, p.radix_bits, p.z, "memory", meter)
    else:
        raise ValueError(method)
    return meter.trace


def simulate_view(method: str, n: int, p: RouterParams | None = None, seed: int = 0) -> list[tuple]:
    """The same trace from the length alone."""
    return kernel_view(method, np.zeros(n, np.uint64), p, seed)


def addresses(view: list[tuple]) -> np.ndarray:
    """The places that a kernel's view touches, in order: both partners of each comparator, and what transpositions read and write.

    Layers over pieces that don't touch each other are taken piece by piece, as tasks would run them.
    """
    out, i = [], 0
    while i < len(view):
        what, *shape = view[i]
        if what == "exchange":
            n, m = shape[0], shape[1]
            j = i
            while j < len(view) and view[j][0] == "exchange" and tuple(view[j][1:3]) == (n, m):
                j += 1
            layers = []
            for _, _, _, _, gap in view[i:j]:
                first = np.arange(m).reshape(-1, 2, gap)[:, 0].ravel()
                layers.append(np.stack((first, first + gap), axis=1).ravel())
            piece = np.concatenate(layers)
            out.append((np.arange(0, n, m)[:, None] + piece[None, :]).ravel())
            i = j
            continue
        if what == "transpose":
            rows, cols = shape
            at = np.arange(rows * cols)
            out.append(np.stack((at, rows * cols + at % cols * rows + at // cols), axis=1).ravel())
        elif what == "place":
            out.append(np.arange(shape[0] * shape[1] * shape[2]))
        i += 1
    return np.concatenate(out) if out else np.empty(0, np.int64)


def misses(method: str, n: int, m: int, b: int, p: RouterParams | None = None) -> int:
    """Misses of a least-recently-used cache of ``m`` places in lines of ``b`` over a kernel's view of length n."""
    from .bounds import CacheSim

    return CacheSim(m, b).replay(addresses(simulate_view(method, n, p)))


def same_distribution(a, b) -> float:
    """Greatest distance of two samples' distribution functions (Kolmogorov and Smirnov), times the root of the joint size: beyond 1.95 in 1 of 1,000 equal pairs."""
    a, b = np.sort(a), np.sort(b)
    at = np.concatenate((a, b))
    gap = np.abs(np.searchsorted(a, at, "right") / len(a) - np.searchsorted(b, at, "right") / len(b)).max()
    return float(gap * np.sqrt(len(a) * len(b) / (len(a) + len(b))))


def kernel_permutation(keys: np.ndarray, p: RouterParams, seed: int, level: str = "cluster") -> tuple[np.ndarray, np.ndarray]:
    """(order, loads): the permutation that router and tags make of ``keys``, and the loads of its bins, which show."""
    from ..operators.permute import spread

    n = len(keys)
    s = K.Slab(np.arange(n, dtype=np.uint64)[:, None].copy(), np.ones(n, bool), keys.astype(np.uint64).view(np.uint8).reshape(n, 8).copy())
    full = spread(s, p.beta, p.z)
    label = (K.coins(full.words[:, 0], 1, seed, 1)[:, 0] >> np.uint64(64 - p.bits)).astype(np.int64) if p.bits else np.zeros(len(full), np.int64)
    routed = K.route_recursive(full, label, p.bits, p.radix_bits, p.z, level)
    loads = routed.real.reshape(p.beta, p.z).sum(1)
    done = K.tag_sort(routed, p.z, K.coins(routed.words[:, 0], p.tag_words, seed, 2), level, K.Meter())
    return done.rec.view(np.uint64).ravel()[done.real], loads


def _tested(orders: list[tuple[np.ndarray, np.ndarray]], n: int) -> tuple[np.ndarray, np.ndarray]:
    """(counts of place by origin, sums of what else is tested) of some permutations with their loads."""
    seen, sums = np.zeros((n, n)), np.zeros(8)
    for order, load in orders:
        seen[np.arange(n), order] += 1
        x, y = float(load.max()), float(order[: n // 2].sum())
        sums += (1, (order == np.arange(n)).sum(), np.corrcoef(order[:-1], order[1:])[0, 1], x, y, x * x, y * y, x * y)
    return seen, sums


def _uniformity(seen: np.ndarray, sums: np.ndarray) -> dict[str, float]:
    n, (runs, fixed, serial, x, y, xx, yy, xy) = len(seen), sums
    chi = ((seen - runs / n) ** 2 / (runs / n)).sum()
    free = (n - 1) ** 2
    spread = (runs * xx - x * x) * (runs * yy - y * y)
    tie = 0.0 if spread <= 0 else float((runs * xy - x * y) / np.sqrt(spread))
    return {"chi_squared": float((chi - free) / np.sqrt(2 * free)), "fixed_points": float(fixed / runs), "serial": float(serial / runs), "load_and_order": tie}


def uniformity_report(n: int, runs: int, p: RouterParams) -> dict[str, float]:
    """Over ``runs`` permutations of n: chi-squared of place by origin in deviations of its mean, mean fixed points (1), mean serial correlation (-1 / n), and the correlation of bin loads with the order's first half."""
    drawn = (kernel_permutation(np.arange(n), p, seed) for seed in range(runs))
    return _uniformity(*_tested([(order.astype(np.int64), load) for order, load in drawn], n))


def table_uniformity(keys: DataFrame, n: int, runs: int, p: RouterParams) -> dict[str, float]:
    """The same over permutations of every block of n rows of a table of different keys, each with fresh coins, in as many turns as make ``runs`` permutations.

    The last rows of a task are filled up with keys beyond the greatest.
    """
    import pyarrow as pa
    from pyspark import TaskContext

    from .shared import ship_package

    total = keys.count()
    turns = -(-runs // max(1, total // n))

    def kernel(batches):
        me, at, held = TaskContext.get().partitionId(), 0, np.empty(0, np.uint64)
        seen, sums = np.zeros((n, n)), np.zeros(8)

        def block(x: np.ndarray) -> None:
            nonlocal at, seen, sums
            order = np.argsort(x)
            drawn = (kernel_permutation(x, p, (me << 40) + at * turns + i) for i in range(turns))
            a, b = _tested([(order[np.searchsorted(x, got, sorter=order)], load) for got, load in drawn], n)
            seen, sums, at = seen + a, sums + b, at + 1

        for batch in batches:
            held = np.concatenate((held, batch.column(0).to_numpy(zero_copy_only=False).astype(np.uint64)))
            full = len(held) // n * n
            for x in held[:full].reshape(-1, n):
                block(x)
            held = held[full:]
        if len(held):
            block(np.concatenate((held, held.max() + np.uint64(1) + np.arange(n - len(held), dtype=np.uint64))))
        yield pa.record_batch([pa.array([seen.ravel().tolist()]), pa.array([sums.tolist()])], names=["seen", "sums"])

    ship_package(keys.sparkSession)
    got = keys.mapInArrow(kernel, "seen array<double>, sums array<double>").collect()
    return _uniformity(sum(np.array(r["seen"]).reshape(n, n) for r in got), sum(np.array(r["sums"]) for r in got))


class SparkMeter:
    """What jobs cost meanwhile, from the session's own store: stages, tasks, exchanged bytes and rows, spilled bytes, seconds."""

    def __init__(self, spark):
        self.spark, self.cost = spark, {}

    def _totals(self) -> dict[str, int]:
        import time

        jvm = self.spark.sparkContext._jsc.sc()
        jvm.listenerBus().waitUntilEmpty(10_000)
        store, out = jvm.statusStore(), {"stages": 0, "tasks": 0, "exchanged_bytes": 0, "exchanged_rows": 0, "spilled_bytes": 0}
        found = store.stageList(None, False, False, getattr(store, "stageList$default$4")(), getattr(store, "stageList$default$5")())
        for i in range(found.size()):
            x = found.apply(i)
            out["stages"] += 1
            out["tasks"] += x.numCompleteTasks()
            out["exchanged_bytes"] += x.shuffleWriteBytes()
            out["exchanged_rows"] += x.shuffleWriteRecords()
            out["spilled_bytes"] += x.diskBytesSpilled()
        return out | {"seconds": time.time()}

    def __enter__(self):
        self.before = self._totals()
        return self

    def __exit__(self, *_):
        after = self._totals()
        self.cost = {k: after[k] - v for k, v in self.before.items()}
        return False


def view_distance(a: list, b: list) -> float:
    """Total variation distance of two traces as bags of events; 0 for equal views."""
    x, y = Counter(a), Counter(b)
    total = max(1, sum(x.values()) + sum(y.values()))
    return sum(abs(x[k] - y[k]) for k in x.keys() | y.keys()) / total


def job_view(df: DataFrame) -> list[tuple[int, int, int]]:
    """(partition, rows, bytes) of what each task would hand on: rows of the DataFrame and the bytes of its binary blocks, if it has any."""
    from pyspark.sql import functions as F

    sizes = [F.octet_length(f.name) for f in df.schema if f.dataType.simpleString() in ("binary", "string")]
    total = sum((F.coalesce(s, F.lit(0)) for s in sizes), F.lit(0))
    got = df.select(F.spark_partition_id().alias("p"), total.alias("b")).groupBy("p").agg(F.count(F.lit(1)).alias("n"), F.sum("b").alias("b"))
    return sorted((r["p"], r["n"], int(r["b"])) for r in got.collect())


class SecretExchange(AssertionError):
    """A plan moves rows by something that isn't public."""


#: Columns that plans of this package may exchange rows by: numbers of blocks, tasks, partitions, nodes, slots and places, and ids that were drawn at random or permuted.
PUBLIC = (
    "_blk", "_blk0", "_dest", "dest", "_pid", "_p", "_pos", "pos", "_task", "_seg", "_run", "_q", "_at", "_a", "_b", "_i", "_j", "_k", "k", "node", "slot", "_n", "_s", "at", "d",
    "x", "s", "_x", "_o", "y", "p", "_c", "_own_id", "pid", "lid", "_l", "_h", "gp", "parent_id", "node_id", "_row", "_off",
)


def assert_public_plan(df: DataFrame, public: tuple[str, ...] = PUBLIC, secret: tuple[str, ...] = ()) -> None:
    """Refuse a plan with a hash exchange on any column that isn't declared public, or that the caller names as secret."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    for found in re.findall(r"hashpartitioning\(([^)]*)\)", plan):
        for name in re.findall(r"([A-Za-z_]\w*)#\d+", found):
            if name not in public or name in secret:
                raise SecretExchange(f"rows are exchanged by {name}")


class guarded:  # noqa: N801  used as a with-statement
    """Every table that is written meanwhile must come of a public plan; columns of the given tables never count as public, whatever their names."""

    def __init__(self, *tables: DataFrame, public: tuple[str, ...] = PUBLIC):
        self.secret, self.public, self.seen = tuple(c for t in tables for c in t.columns), public, 0

    def _look(self, df: DataFrame) -> None:
        self.seen += 1
        assert_public_plan(df, self.public, self.secret)

    def __enter__(self):
        from . import shared

        shared._watchers.append(self._look)
        return self

    def __exit__(self, *_):
        from . import shared

        shared._watchers.remove(self._look)
        return False


#: Settings under which a plan's shape doesn't follow the data. All can be set on a running session.
OBLIVIOUS_CONF = {
    "spark.sql.adaptive.enabled": "false", "spark.sql.sort.enableRadixSort": "false", "spark.sql.autoBroadcastJoinThreshold": "-1",
    "spark.sql.parquet.filterPushdown": "false", "spark.sql.optimizer.runtime.bloomFilter.enabled": "false", "spark.sql.parquet.compression.codec": "uncompressed",
}


class oblivious_session:  # noqa: N801  used as a with-statement
    """The settings above, put back afterwards."""

    def __init__(self, spark):
        self.spark, self.before = spark, {}

    def __enter__(self):
        for k, v in OBLIVIOUS_CONF.items():
            self.before[k] = self.spark.conf.get(k, None)
            self.spark.conf.set(k, v)
        return self.spark

    def __exit__(self, *_):
        for k, v in self.before.items():
            self.spark.conf.unset(k) if v is None else self.spark.conf.set(k, v)
        return False
