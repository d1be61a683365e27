"""The experiment workloads on the given tables: queries, and DuckDB SQL for the same rows.

Coins are keyed hashes under a fixed seed, so that results can be compared; kernels run at the cluster level but where a name says otherwise.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import sources, streaming
from .functions import kernels as K
from .functions.codec import Key, as_keys
from .operators import baselines, graphs, pram, primitives, relational, sorts, tree_memory
from .operators.permute import permute, route_bins
from .plans import bounds, params, trace
from .plans.components import connected_components as star_components
from .plans.shared import dense_positions, materialise, numbered, ship_package

S = {"seed": 7, "level": "cluster"}
LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
NARROW = {"l_returnflag": 1, "l_linestatus": 1}

_QUERIES: dict = {}
_ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        _QUERIES[name or f.__name__] = f
        if sql is not None:
            _ORACLES[name or f.__name__] = sql
        return f

    return add


def t(spark: SparkSession, d: str, table: str) -> DataFrame:
    return sources.read(spark, f"{d}/{table}.parquet")


def cents(c: str):
    return F.round(F.col(c) * 100).cast("long")


# -- sorts ------------------------------------------------------------------------------------------------------

_LINE_RANKS = f"""SELECT row_number() OVER (ORDER BY {', '.join(LINE)}) - 1 AS rank, l_orderkey, l_linenumber, l_partkey, l_extendedprice FROM lineitem"""


def _line_ranks(df: DataFrame) -> DataFrame:
    return df.select(F.col("pos").alias("rank"), "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice")


@query(_LINE_RANKS)
def sort_lineitem_engine(spark, d):
    return _line_ranks(sorts.oblivious_sort(t(spark, d, "lineitem").select(LINE), LINE, widths=NARROW, **S))


@query(_LINE_RANKS)
def sort_lineitem_two_exchanges(spark, d):
    return _line_ranks(sorts.oblivious_sort(t(spark, d, "lineitem").select(LINE), LINE, widths=NARROW, phases=2, **S))


@query(_LINE_RANKS)
def sort_lineitem_pivots(spark, d):
    return _line_ranks(sorts.oblivious_sort(t(spark, d, "lineitem").select(LINE), LINE, second="pivots", widths=NARROW, **S))


@query(_LINE_RANKS)
def sort_relaxed_pivots(spark, d):
    return _line_ranks(sorts.oblivious_sort(t(spark, d, "lineitem").select(LINE), LINE, second="pivots", relaxed=True, widths=NARROW, **S))


@query(_LINE_RANKS)
def baseline_engine_sort(spark, d):
    return _line_ranks(baselines.engine_sort(t(spark, d, "lineitem").select(LINE), LINE))


_ORDER_RANKS = "SELECT row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) - 1 AS rank, o_orderkey FROM orders"
_PRICE = [Key("o_totalprice", False), Key("o_orderkey")]


def _orders(spark, d):
    return t(spark, d, "orders").select("o_orderkey", "o_totalprice")


def _order_ranks(df: DataFrame) -> DataFrame:
    return df.select(F.col("pos").alias("rank"), "o_orderkey")


@query(_ORDER_RANKS)
def sort_orders_price_desc(spark, d):
    return _order_ranks(sorts.oblivious_sort(_orders(spark, d), _PRICE, **S))


@query(_ORDER_RANKS)
def sort_orders_memory_level(spark, d):
    return _order_ranks(sorts.oblivious_sort(_orders(spark, d), _PRICE, seed=7, level="memory"))


@query(_ORDER_RANKS)
def sort_gamma2(spark, d):
    return _order_ranks(sorts.oblivious_sort(_orders(spark, d), _PRICE, gamma=2, form="layered", **S))


@query(_ORDER_RANKS)
def sort_permuted_only(spark, d):
    return _order_ranks(sorts.sort_permuted(permute(_orders(spark, d), **S), _PRICE, seed=7))


@query("SELECT row_number() OVER (ORDER BY p_retailprice, p_partkey) - 1 AS rank, p_partkey FROM part")
def sort_optimal_billed(spark, d):
    df = t(spark, d, "part").select("p_partkey", "p_retailprice")
    done = sorts.oblivious_sort(df, ["p_retailprice", "p_partkey"], second="pivots", network="search", **S)
    return done.select(F.col("pos").alias("rank"), "p_partkey")


@query("SELECT row_number() OVER (ORDER BY text, doc_id) - 1 AS rank, doc_id FROM documents")
def sort_documents_text(spark, d):
    return sorts.sort_by_text(t(spark, d, "documents"), "text", "doc_id", **S).select(F.col("pos").alias("rank"), "doc_id")


@query('SELECT row_number() OVER (ORDER BY "value", event_id) - 1 AS rank, event_id FROM events')
def sort_events_recursive_bitonic(spark, d):
    df = t(spark, d, "events").select("event_id", "value")
    return sorts.bitonic_sort(df, ["value", "event_id"]).select(F.col("pos").alias("rank"), "event_id")


@query("SELECT row_number() OVER (ORDER BY c_acctbal, c_custkey) - 1 AS rank, c_custkey FROM customer")
def sort_customer_layered_bitonic(spark, d):
    df = t(spark, d, "customer").select("c_custkey", "c_acctbal")
    return sorts.bitonic_sort(df, ["c_acctbal", "c_custkey"], merge="layered").select(F.col("pos").alias("rank"), "c_custkey")


@query("SELECT row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS rank, o_orderkey FROM orders")
def bitonic_merge_two_runs(spark, d):
    """A rising run, fillers and a falling run are bitonic: one merge across tasks."""
    up, down = (dense_positions(_orders(spark, d).filter(F.col("o_orderkey") % 2 == i), [F.col("o_totalprice"), F.col("o_orderkey")], "at") for i in (0, 1))
    length = params.power_of_two(_orders(spark, d).count())
    both = up.unionByName(down.withColumn("at", F.lit(length - 1) - F.col("at")))
    return sorts.bitonic_merge(both, ["o_totalprice", "o_orderkey"], "at", length).select(F.col("pos").alias("rank"), "o_orderkey")


@query(_ORDER_RANKS)
def sort_layered_pivots(spark, d):
    """Pivots of a sample that the network sorts, routed layer by layer, rows sorted together with pivots by the network."""
    return _order_ranks(sorts.sort_permuted(permute(_orders(spark, d), **S), _PRICE, seed=7, form="layered", router="bitonic", sampler="bitonic"))


# -- permutation, routing, placement -----------------------------------------------------------------------------


@query("SELECT count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS keys, count(*) AS places, CAST(0 AS BIGINT) AS first, count(*) - 1 AS last FROM orders")
def permute_orders_invariants(spark, d):
    placed = dense_positions(permute(_orders(spark, d), **S).take(), [F.col("_task"), F.col("_at")], "pos")
    return placed.agg(F.count(F.lit(1)).alias("n"), F.sum("o_orderkey").alias("keys"), F.countDistinct("pos").alias("places"), F.min("pos").alias("first"), F.max("pos").alias("last"))


_LABEL = "(l_orderkey * 31 + l_partkey * 17 + l_suppkey * 7 + l_linenumber)"
_ROUTED = f"""WITH z AS (SELECT count(*) AS n, greatest(16, pow(2, ceil(log2(log2(count(*)) * log2(count(*)))))) AS z FROM lineitem),
b AS (SELECT CAST(pow(2, ceil(log2(2 * n / z))) AS BIGINT) AS beta FROM z)
SELECT {_LABEL} % beta AS bin, count(*) AS reals, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem, b GROUP BY 1"""


def _routed(spark, d, form):
    df = t(spark, d, "lineitem")
    p = params.from_length(df.count())
    df = df.select(F.expr(f"{_LABEL} % {p.beta}").alias("label"), cents("l_extendedprice").alias("c"))
    got = route_bins(df, "label", p, level="cluster", form=form)
    return got.groupBy(F.col("_bin").alias("bin")).agg(F.count(F.lit(1)).alias("reals"), F.sum("c").alias("cents"))


@query(_ROUTED)
def route_bins_by_label(spark, d):
    return _routed(spark, d, "layered")


@query(_ROUTED)
def route_bins_recursive(spark, d):
    return _routed(spark, d, "recursive")


@query(
    """WITH c AS (SELECT CAST(greatest(16, pow(2, ceil(log2(2 * count(*) / 25.0)))) AS BIGINT) AS cap FROM customer),
r AS (SELECT c_nationkey AS bin, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) - 1 AS slot, c_custkey FROM customer)
SELECT CAST(b.b AS INTEGER) AS bin, s.s AS slot, r.c_custkey IS NOT NULL AS is_real, r.c_custkey
FROM c, generate_series(0, 24) b(b), LATERAL (SELECT unnest(generate_series(0, cap - 1)) AS s) s LEFT JOIN r ON r.bin = b.b AND r.slot = s.s"""
)
def place_bins_by_nation(spark, d):
    df = t(spark, d, "customer").select(F.col("c_nationkey").alias("bin"), "c_custkey", F.col("c_custkey").alias("pos"))
    cap = max(16, params.power_of_two(2 * df.count() / 25))
    return primitives.place_bins(df, "bin", 25, cap, **S).select("bin", "slot", "is_real", "c_custkey")


@query("SELECT p_partkey % (SELECT count(*) // 40 FROM part) AS row, p_partkey // (SELECT count(*) // 40 FROM part) AS col, p_partkey FROM part")
def transpose_part_matrix(spark, d):
    df = t(spark, d, "part").select("p_partkey", F.col("p_partkey").alias("pos"))
    return primitives.transpose(df, 40, df.count() // 40).select("row", "col", "p_partkey")


@query("SELECT row_number() OVER (ORDER BY o_orderkey) - 1 AS pos, o_orderkey FROM orders WHERE o_orderstatus = 'O'")
def compact_open_orders(spark, d):
    df = t(spark, d, "orders").select("o_orderkey", "o_orderstatus", F.col("o_orderkey").alias("pos"))
    return primitives.compact(df, F.col("o_orderstatus") == "O", **S).filter("NOT is_filler").select("pos", "o_orderkey")


_PIVOTS = (1000.0, 5000.0, 10000.0, 20000.0, 30000.0, 40000.0, 50000.0)


_REGIONS = f"SELECT CAST(({' + '.join(f'(l_extendedprice > {p})::INT' for p in _PIVOTS)}) AS BIGINT) AS bin, count(*) AS n, min(l_extendedprice) AS least, max(l_extendedprice) AS most FROM lineitem GROUP BY 1"


def _regions(spark, d, **how):
    """The permuted lines routed by given pivots, which come after all rows of their price."""
    rows = permute(t(spark, d, "lineitem").select("l_extendedprice"), **S).take()
    pivots = spark.createDataFrame([(p, (1 << 31) - 1, (1 << 62), i) for i, p in enumerate(_PIVOTS)], "l_extendedprice double, _task int, _at long, _p long")
    got = sorts.route_by_pivots(rows, pivots, len(_PIVOTS), ["l_extendedprice"], **how)
    return got.groupBy(F.col("_bin").alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.min("l_extendedprice").alias("least"), F.max("l_extendedprice").alias("most"))


@query(_REGIONS)
def pivot_regions(spark, d):
    return _regions(spark, d, network="bitonic")


@query(_REGIONS)
def pivot_regions_layered(spark, d):
    return _regions(spark, d, form="layered", gamma=2)


@query("SELECT count(*) AS n, true AS in_order, true AS within FROM lineitem")
def pivot_loads(spark, d):
    """Pivots of the table itself: regions follow each other, and none is above the bound on its load."""
    rows = materialise(permute(t(spark, d, "lineitem").select("l_extendedprice"), **S).take(), "permuted")
    n = rows.count()
    pivots = materialise(sorts.choose_pivots(rows, as_keys(["l_extendedprice"]), n, seed=7), "pivots")
    got = materialise(sorts.route_by_pivots(rows, pivots, pivots.count(), ["l_extendedprice"]), "regions")
    loads = got.groupBy("_bin").agg(F.count(F.lit(1)).alias("load"), F.min("l_extendedprice").alias("least"), F.max("l_extendedprice").alias("most"))
    before = dense_positions(loads, [F.col("_bin")], "_i")
    after = before.select((F.col("_i") - 1).alias("_j"), F.col("least").alias("next"))
    pairs = before.join(after, F.col("_i") == F.col("_j"), "left")
    return pairs.agg(F.sum("load").alias("n"), F.bool_and(F.col("next").isNull() | (F.col("most") <= F.col("next"))).alias("in_order"), (F.max("load") <= params.pivot_bin_bound(n)).alias("within"))


# -- aggregation and propagation -----------------------------------------------------------------------------------


@query(
    f"""SELECT rank, l_orderkey, CAST(coalesce(sum(c) OVER (PARTITION BY l_orderkey ORDER BY rank ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0) AS BIGINT) AS ahead
FROM (SELECT row_number() OVER (ORDER BY {', '.join(LINE)}) - 1 AS rank, l_orderkey, CAST(round(l_extendedprice * 100) AS BIGINT) AS c FROM lineitem)"""
)
def suffix_sum_order_lines(spark, d):
    rows = materialise(sorts.oblivious_sort(t(spark, d, "lineitem").select(LINE), LINE, widths=NARROW, **S), "lines")
    return primitives.segmented_aggregate(rows, ["l_orderkey"], cents("l_extendedprice"), "sum", "ahead").select(F.col("pos").alias("rank"), "l_orderkey", "ahead")


_EVENTS = ["user_id", "ts", "event_id"]


def _user_events(spark, d):
    return materialise(sorts.oblivious_sort(t(spark, d, "events").select(*_EVENTS, "value"), _EVENTS, **S), "events")


@query('SELECT event_id, max("value") OVER w AS most, min("value") OVER w AS least FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING)')
def suffix_max_user_events(spark, d):
    rows = primitives.segmented_aggregate(_user_events(spark, d), ["user_id"], F.col("value"), "max", "most")
    return primitives.segmented_aggregate(rows, ["user_id"], F.col("value"), "min", "least").select("event_id", "most", "least")


@query("SELECT o_orderkey, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM orders")
def aggregate_prefix_inclusive(spark, d):
    df = t(spark, d, "orders").select("o_custkey", "o_orderdate", "o_orderkey", "o_totalprice")
    rows = materialise(sorts.oblivious_sort(df, ["o_custkey", "o_orderdate", "o_orderkey"], **S), "orders")
    return primitives.segmented_aggregate(rows, ["o_custkey"], cents("o_totalprice"), "sum", "running", True, "prefix").select("o_orderkey", "running")


@query('SELECT event_id, CAST(sum(CAST(round("value" * 100) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM events')
def aggregate_doubling_baseline(spark, d):
    return baselines.doubling_aggregate(_user_events(spark, d), ["user_id"], cents("value"), "running").select("event_id", "running")


@query("SELECT o_orderkey, first_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS first_order FROM orders")
def propagate_first_order(spark, d):
    df = t(spark, d, "orders").select("o_custkey", "o_orderdate", "o_orderkey")
    rows = materialise(sorts.oblivious_sort(df, ["o_custkey", "o_orderdate", "o_orderkey"], **S), "orders")
    return primitives.propagate(rows, ["o_custkey"], F.col("o_orderkey"), "first_order").select("o_orderkey", "first_order")


@query("SELECT conv_id, turn, first_value(role) OVER (PARTITION BY conv_id ORDER BY turn) AS opening FROM conversations")
def propagate_conv_opening(spark, d):
    rows = sorts.oblivious_sort(t(spark, d, "conversations").select("conv_id", "turn", "role"), ["conv_id", "turn"], **S)
    return primitives.propagate(rows, ["conv_id"], F.col("role"), "opening").select("conv_id", "turn", "opening")


@query("SELECT o_orderkey, c_acctbal, c_mktsegment FROM orders LEFT JOIN customer ON o_custkey = c_custkey")
def send_receive_order_customer(spark, d):
    senders = t(spark, d, "customer").select(F.col("c_custkey").alias("k"), "c_acctbal", "c_mktsegment")
    return primitives.send_receive(senders, t(spark, d, "orders").select(F.col("o_custkey").alias("k"), "o_orderkey"), ["k"], ["c_acctbal", "c_mktsegment"], **S).select("o_orderkey", "c_acctbal", "c_mktsegment")


@query("SELECT o_orderkey, c_acctbal FROM orders LEFT JOIN customer ON o_custkey = c_custkey")
def baseline_send_receive_network(spark, d):
    """The earlier method: the same send-receive on the bitonic network."""
    senders = t(spark, d, "customer").select(F.col("c_custkey").alias("k"), "c_acctbal")
    asked = t(spark, d, "orders").select(F.col("o_custkey").alias("k"), "o_orderkey")
    return primitives.send_receive(senders, asked, ["k"], ["c_acctbal"], sorter=sorts.bitonic_sort, restore=False).select("o_orderkey", "c_acctbal")


@query("SELECT o_orderkey, c_acctbal, c_mktsegment FROM orders LEFT JOIN customer ON o_custkey = c_custkey")
def baseline_join(spark, d):
    cust = t(spark, d, "customer").select("c_custkey", "c_acctbal", "c_mktsegment")
    return baselines.plain_join(t(spark, d, "orders").select("o_orderkey", "o_custkey"), cust, "o_custkey", "c_custkey", "left").select("o_orderkey", "c_acctbal", "c_mktsegment")


@query("SELECT d.doc_id, quality, toxic, l.doc_id IS NOT NULL AS found FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def send_receive_labels_missing(spark, d):
    return primitives.send_receive(t(spark, d, "labels"), t(spark, d, "documents").select("doc_id"), ["doc_id"], ["quality", "toxic"], **S)


@query("SELECT a.conv_id, a.turn, b.role AS before FROM conversations a LEFT JOIN conversations b ON a.conv_id = b.conv_id AND a.turn = b.turn + 1")
def send_receive_composite(spark, d):
    conv = t(spark, d, "conversations")
    senders = conv.select("conv_id", (F.col("turn") + 1).alias("turn"), F.col("role").alias("before"))
    return primitives.send_receive(senders, conv.select("conv_id", "turn"), ["conv_id", "turn"], ["before"], **S).drop("found")


@query(f"SELECT rank, row_number() OVER (ORDER BY rank) - 1 AS new_index FROM (SELECT row_number() OVER (ORDER BY {', '.join(LINE)}) - 1 AS rank, l_extendedprice FROM lineitem) WHERE l_extendedprice > 40000")
def prefix_renumber_high_value(spark, d):
    rows = materialise(sorts.oblivious_sort(t(spark, d, "lineitem").select(LINE), LINE, widths=NARROW, **S), "lines")
    return primitives.renumber(rows, F.col("l_extendedprice") > 40000, "new_index").filter("new_index IS NOT NULL").select(F.col("pos").alias("rank"), "new_index")


# -- memory steps --------------------------------------------------------------------------------------------------


@query("SELECT l_orderkey, l_linenumber, l_partkey, p_retailprice AS price FROM lineitem LEFT JOIN part ON l_partkey = p_partkey")
def pram_read_prices(spark, d):
    mem = t(spark, d, "part").select(F.col("p_partkey").alias("addr"), F.col("p_retailprice").alias("val"))
    got = pram.pram_read(mem, t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.col("l_partkey").alias("addr")), **S)
    return got.select("l_orderkey", "l_linenumber", F.col("addr").alias("l_partkey"), F.col("val").alias("price"))


def _balances(spark, d):
    mem = t(spark, d, "customer").select(F.col("c_custkey").alias("addr"), cents("c_acctbal").alias("val"))
    return mem, t(spark, d, "orders").select(F.col("o_orderkey").alias("proc"), F.col("o_custkey").alias("addr"), cents("o_totalprice").alias("val"))


def _written(spark, d, rule):
    mem, req = _balances(spark, d)
    return pram.pram_write(mem, req, rule, **S).select(F.col("addr").alias("c_custkey"), "val")


def _write_sql(agg: str) -> str:
    return f"""SELECT c_custkey, coalesce(v, CAST(round(c_acctbal * 100) AS BIGINT)) AS val FROM customer LEFT JOIN
(SELECT o_custkey, CAST({agg} AS BIGINT) AS v FROM (SELECT *, CAST(round(o_totalprice * 100) AS BIGINT) AS c FROM orders) GROUP BY 1) ON c_custkey = o_custkey"""


@query(_write_sql("arg_min(c, o_orderkey)"))
def pram_write_priority(spark, d):
    return _written(spark, d, "priority")


@query(_write_sql("sum(c)"))
def pram_write_combine_sum(spark, d):
    return _written(spark, d, "sum")


@query(_write_sql("max(c)"))
def pram_write_combine_max(spark, d):
    return _written(spark, d, "max")


@query(_write_sql("min(c)"))
def pram_write_combine_min(spark, d):
    return _written(spark, d, "min")


@query("SELECT c_custkey, CASE WHEN o_custkey IS NULL THEN CAST(round(c_acctbal * 100) AS BIGINT) ELSE c_custkey * 3 END AS val FROM customer LEFT JOIN (SELECT DISTINCT o_custkey FROM orders) ON c_custkey = o_custkey")
def pram_write_common(spark, d):
    mem, req = _balances(spark, d)
    return pram.pram_write(mem, req.withColumn("val", F.col("addr") * 3), "common", **S).select(F.col("addr").alias("c_custkey"), "val")


def _size_cells(spark, d):
    n = t(spark, d, "part").groupBy((F.col("p_size") - 1).cast("long").alias("_a")).agg(F.count(F.lit(1)).alias("_c"))
    cells = spark.range(50).select(F.col("id").alias("addr"))
    return cells.join(F.broadcast(n), F.col("addr") == F.col("_a"), "left").select("addr", F.coalesce("_c", F.lit(0)).alias("val"))


_SIZES = "SELECT c.c AS cell, count(p_size) AS k FROM generate_series(0, 49) c(c) LEFT JOIN part ON p_size = c.c + 1 GROUP BY 1"


@query(f"SELECT cell, CAST(sum(k) OVER (ORDER BY cell) AS BIGINT) AS value FROM ({_SIZES})")
def pram_program_prefix_sum(spark, d):
    mem, _ = pram.run_pram(pram.prefix_sum_program(50), _size_cells(spark, d), spark.range(50).select(F.col("id").alias("proc")), **S)
    return mem.select(F.col("addr").alias("cell"), F.col("val").alias("value"))


@query(f"SELECT CAST(0 AS BIGINT) AS cell, max(k) AS value FROM ({_SIZES})")
def pram_program_max(spark, d):
    mem, _ = pram.run_pram(pram.max_program(50), _size_cells(spark, d), spark.range(50).select(F.col("id").alias("proc")), **S)
    return mem.filter("addr = 0").select(F.col("addr").alias("cell"), F.col("val").alias("value"))


_USERS = "SELECT CAST(c.c AS BIGINT) AS cell, count(user_id) AS value FROM generate_series(0, greatest(149, (SELECT max(user_id) FROM events))) c(c) LEFT JOIN events ON user_id = c.c GROUP BY 1"


def _user_cells(spark, d) -> DataFrame:
    """A cell of 0 for each user from 0 to the greatest id, 150 at least as the SQL lists them."""
    most = t(spark, d, "events").agg(F.max("user_id")).first()[0]
    return spark.range(max(150, 1 + (-1 if most is None else most))).select(F.col("id").alias("addr"), F.lit(0).cast("long").alias("val"))


@query("SELECT n_nationkey::BIGINT AS cell, max(n_nationkey::BIGINT) OVER (PARTITION BY n_regionkey) AS value FROM nation")
def pram_program_pointer_jump(spark, d):
    """Every nation points to the next of its region; after the jumps, to the last."""
    n = t(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("id"), "n_regionkey")
    chain = relational.neighbour(n, ["n_regionkey"], ["id"], F.col("id"), "next", -1, **S)
    mem = materialise(chain.select(F.col("id").alias("addr"), F.coalesce("next", "id").alias("val")), "chain")
    mem, _ = pram.run_pram(pram.pointer_jump_program(25), mem, n.select(F.col("id").alias("proc")), **S)
    return mem.select(F.col("addr").alias("cell"), F.col("val").alias("value"))


@query(_USERS)
def pram_program_histogram(spark, d):
    procs = t(spark, d, "events").select(F.col("event_id").alias("proc"), F.col("user_id").alias("key"))
    mem, _ = pram.run_pram(pram.histogram_program(), _user_cells(spark, d), procs, **S)
    return mem.select(F.col("addr").alias("cell"), F.col("val").alias("value"))


def _requests(df: DataFrame, op: str) -> DataFrame:
    return df.select(F.col("proc").alias("i"), F.lit(op).alias("op"), "addr", (F.col("val") if op == "w" else F.lit(None)).cast("long").alias("val"))


@query("SELECT l_orderkey, l_linenumber, l_partkey, CAST(round(p_retailprice * 100) AS BIGINT) AS val FROM lineitem LEFT JOIN part ON l_partkey = p_partkey")
def treemem_read_batch(spark, d):
    """Every line reads its part's price; trees keep all but their first seven levels."""
    mem = tree_memory.TreeMemory(t(spark, d, "part").select(F.col("p_partkey").alias("addr"), cents("p_retailprice").alias("val")), top=7, **S)
    lines = materialise(numbered(t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey"), "proc"), "lines")
    got = mem.access(_requests(lines.select("proc", F.col("l_partkey").alias("addr"), F.lit(0).alias("val")), "r"))
    return lines.join(got, F.col("proc") == F.col("i")).select("l_orderkey", "l_linenumber", "l_partkey", "val")


@query(
    """WITH w AS (SELECT o_custkey, arg_min(CAST(round(o_totalprice * 100) AS BIGINT), o_orderkey) AS v FROM orders GROUP BY 1)
SELECT c_custkey, coalesce(v, CAST(round(c_acctbal * 100) AS BIGINT)) AS val FROM customer LEFT JOIN w ON c_custkey = o_custkey"""
)
def treemem_write_then_read(spark, d):
    """Every order writes its price to its customer's cell, the least order number winning; then every customer is read."""
    cells, req = _balances(spark, d)
    mem = tree_memory.TreeMemory(cells, top=7, **S)
    mem.access(_requests(req, "w"))
    return mem.access(_requests(cells.select(F.col("addr").alias("proc"), "addr", "val"), "r")).select(F.col("i").alias("c_custkey"), "val")


@query(_USERS)
def simulate_histogram_in_tree(spark, d):
    """The histogram's one combining write in tree memory; the chooser, which counts work, would sort all cells instead."""
    procs = t(spark, d, "events").select(F.col("event_id").alias("proc"), F.col("user_id").alias("key"))
    mem, _ = tree_memory.simulate(pram.histogram_program(), _user_cells(spark, d), procs, "tree", top=5, **S)
    return mem.select(F.col("addr").alias("cell"), F.col("val").alias("value"))


# -- lists and trees ------------------------------------------------------------------------------------------------


def _chain(df: DataFrame, key: str, group: list[str], order: list[str], weight=None) -> DataFrame:
    """(id, succ, w): each row linked to the next of its group; ids are 1 and up."""
    from pyspark.sql import Window

    placed = dense_positions(df, [F.col(c) for c in [*group, *order]], "_i").withColumn("id", F.col("_i") + 1)
    nxt = placed.select((F.col("_i") - 1).alias("_j"), *[F.col(c).alias(f"_g{k}") for k, c in enumerate(group)])
    same = F.col("_j").isNotNull()
    for k, c in enumerate(group):
        same = same & (F.col(c) == F.col(f"_g{k}"))
    linked = placed.join(nxt, F.col("_i") == F.col("_j"), "left")
    return materialise(linked.select("id", F.when(same, F.col("id") + 1).otherwise(F.lit(0)).alias("succ"), key, *([] if weight is None else [weight.alias("w")]), *[c for c in order if c != key]), "chain")


@query("SELECT event_id, count(*) OVER () - row_number() OVER (ORDER BY ts, event_id) AS ahead FROM events")
def list_rank_events_global(spark, d):
    return graphs.list_rank(_chain(t(spark, d, "events"), "event_id", [], ["ts", "event_id"]).drop("ts"), "id", "succ", **S).select("event_id", "ahead")


_USER_CHAINS = "SELECT event_id, count(*) OVER (PARTITION BY user_id) - row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS ahead FROM events"


@query(_USER_CHAINS)
def list_rank_user_chains(spark, d):
    return graphs.list_rank(_chain(t(spark, d, "events"), "event_id", ["user_id"], ["ts", "event_id"]).drop("ts"), "id", "succ", **S).select("event_id", "ahead")


@query(_USER_CHAINS)
def list_rank_splice_rounds(spark, d):
    """The coin-splicing rounds across tasks: only 2,000 nodes may be left to one."""
    return graphs.list_rank(_chain(t(spark, d, "events"), "event_id", ["user_id"], ["ts", "event_id"]).drop("ts"), "id", "succ", tail=2000, **S).select("event_id", "ahead")


@query(_USER_CHAINS)
def list_rank_jump_baseline(spark, d):
    chain = _chain(t(spark, d, "events"), "event_id", ["user_id"], ["ts", "event_id"])
    return baselines.pointer_jump(chain, "id", "succ").join(chain.select("id", "event_id"), "id").select("event_id", "ahead")


@query("SELECT o_orderkey, CAST(coalesce(sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0) AS BIGINT) AS ahead FROM orders")
def list_rank_weighted_orders(spark, d):
    chain = _chain(t(spark, d, "orders"), "o_orderkey", ["o_custkey"], ["o_orderdate", "o_orderkey"], cents("o_totalprice"))
    return graphs.list_rank(chain.drop("o_orderdate"), "id", "succ", weight="w", **S).select("o_orderkey", "ahead")


@query("SELECT conv_id, turn, count(*) OVER (PARTITION BY conv_id) - row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS ahead FROM conversations")
def list_rank_conversations(spark, d):
    chain = _chain(t(spark, d, "conversations").select("conv_id", "turn"), "conv_id", ["conv_id"], ["turn"])
    return graphs.list_rank(chain, "id", "succ", **S).select("conv_id", "turn", "ahead")


def _hierarchy(spark, d, depth: str) -> DataFrame:
    """Edges (a, b), parent first: 0, regions, nations, then customers and suppliers, then orders."""
    edges = t(spark, d, "region").select(F.lit(0).cast("long").alias("a"), (F.col("r_regionkey") + 1).cast("long").alias("b"))
    edges = edges.unionByName(t(spark, d, "nation").select((F.col("n_regionkey") + 1).cast("long").alias("a"), (F.col("n_nationkey") + 6).cast("long").alias("b")))
    if depth == "nation":
        return edges
    cust = t(spark, d, "customer")
    c, s = cust.count(), t(spark, d, "supplier").count()
    edges = edges.unionByName(cust.select((F.col("c_nationkey") + 6).cast("long").alias("a"), (F.col("c_custkey") + 31).alias("b")))
    edges = edges.unionByName(t(spark, d, "supplier").select((F.col("s_nationkey") + 6).cast("long").alias("a"), (F.col("s_suppkey") + 31 + c).alias("b")))
    if depth == "customer":
        return edges
    edges = edges.unionByName(t(spark, d, "orders").select((F.col("o_custkey") + 31).alias("a"), (F.col("o_orderkey") + 31 + c + s).alias("b")))
    if depth == "orders":
        return edges
    # lines have no key of their own: their place in the table names them
    o = t(spark, d, "orders").count()
    lines = numbered(t(spark, d, "lineitem").select("l_orderkey"), "_i")
    return edges.unionByName(lines.select((F.col("l_orderkey") + 31 + c + s).alias("a"), (F.col("_i") + 31 + c + s + o).alias("b")))


_EDGES = {
    "nation": "SELECT CAST(0 AS BIGINT) AS a, CAST(r_regionkey + 1 AS BIGINT) AS b FROM region UNION ALL SELECT CAST(n_regionkey + 1 AS BIGINT), CAST(n_nationkey + 6 AS BIGINT) FROM nation",
}
_EDGES["customer"] = _EDGES["nation"] + " UNION ALL SELECT CAST(c_nationkey + 6 AS BIGINT), c_custkey + 31 FROM customer UNION ALL SELECT CAST(s_nationkey + 6 AS BIGINT), s_suppkey + 31 + (SELECT count(*) FROM customer) FROM supplier"
_EDGES["orders"] = _EDGES["customer"] + " UNION ALL SELECT o_custkey + 31, o_orderkey + 31 + (SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier) FROM orders"


_UP = "(SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier)"
_EDGES["lines"] = _EDGES["orders"] + f" UNION ALL SELECT l_orderkey + 31 + {_UP}, row_number() OVER () + 30 + {_UP} + (SELECT count(*) FROM orders) FROM lineitem"


def _tour_sql(depth: str) -> str:
    return f"""WITH e AS ({_EDGES[depth]}), b AS (SELECT a AS u, b AS v FROM e UNION ALL SELECT b, a FROM e),
c AS (SELECT u, v, coalesce(lead(v) OVER w, first_value(v) OVER w) AS n FROM b WINDOW w AS (PARTITION BY u ORDER BY v))
SELECT b.u, b.v, b.v AS su, c.n AS sv FROM b JOIN c ON c.u = b.v AND c.v = b.u"""


@query(_tour_sql("nation"))
def euler_tour_nations(spark, d):
    return graphs.euler_tour(_hierarchy(spark, d, "nation"), **S)


@query(_tour_sql("customer"))
def euler_tour_customers(spark, d):
    return graphs.euler_tour(_hierarchy(spark, d, "customer"), **S)


@query(_tour_sql("customer"))
def baseline_euler_windows(spark, d):
    return baselines.euler_tour(_hierarchy(spark, d, "customer"))


def _tree_sql(depth: str) -> str:
    """Preorder by padded paths, subtree sizes by path prefixes."""
    return f"""WITH RECURSIVE e AS ({_EDGES[depth]}), w AS (
SELECT CAST(0 AS BIGINT) AS node, CAST(NULL AS BIGINT) AS parent, CAST(0 AS BIGINT) AS depth, [CAST(0 AS BIGINT)] AS path
UNION ALL SELECT e.b, e.a, w.depth + 1, list_append(w.path, e.b) FROM w JOIN e ON e.a = w.node),
s AS (SELECT anc AS node, count(*) AS size FROM (SELECT unnest(path) AS anc FROM w) GROUP BY 1),
p AS (SELECT w.*, s.size, row_number() OVER (ORDER BY path) - 1 AS pre FROM w JOIN s USING (node))
SELECT node, parent, depth, pre, pre + size - 1 - depth AS post, size FROM p"""


@query(_tree_sql("customer"))
def tree_functions_hierarchy(spark, d):
    return graphs.tree_functions(_hierarchy(spark, d, "customer"), 0, **S).drop("is_leaf")


@query(f"SELECT node AS id, size AS total FROM ({_tree_sql('customer')})")
def baseline_rollup_hierarchy(spark, d):
    nodes = _hierarchy(spark, d, "customer").select(F.col("b").alias("id"), F.col("a").alias("parent"), F.lit(1).cast("long").alias("one"))
    top = spark.createDataFrame([(0, None, 1)], "id long, parent long, one long")
    return baselines.rollup_tree(nodes.unionByName(top), "one", 4)


@query(f"SELECT depth, count(*) AS nodes, CAST(sum(size) AS BIGINT) AS sizes, CAST(sum(pre) AS BIGINT) AS pres, CAST(sum(post) AS BIGINT) AS posts FROM ({_tree_sql('orders')}) GROUP BY 1")
def tree_depth_orders(spark, d):
    got = graphs.tree_functions(_hierarchy(spark, d, "orders"), 0, **S)
    return got.groupBy("depth").agg(F.count(F.lit(1)).alias("nodes"), F.sum("size").alias("sizes"), F.sum("pre").alias("pres"), F.sum("post").alias("posts"))


@query(
    f"""WITH e AS ({_EDGES['lines']}), n AS (SELECT b AS node, a AS parent, 1 AS lines FROM e WHERE b >= 31 + {_UP} + (SELECT count(*) FROM orders)),
o AS (SELECT e.b AS node, e.a AS parent, count(n.node) AS lines FROM e LEFT JOIN n ON n.parent = e.b WHERE e.b >= 31 + {_UP} AND e.b < 31 + {_UP} + (SELECT count(*) FROM orders) GROUP BY 1, 2),
c AS (SELECT e.b AS node, e.a AS parent, coalesce(sum(1 + o.lines), 0) AS below FROM e LEFT JOIN o ON o.parent = e.b WHERE e.b >= 31 AND e.b < 31 + {_UP} GROUP BY 1, 2),
k AS (SELECT e.b AS node, e.a AS parent, sum(1 + c.below) AS below FROM e LEFT JOIN c ON c.parent = e.b WHERE e.b BETWEEN 6 AND 30 GROUP BY 1, 2)
SELECT CAST(depth AS BIGINT) AS depth, count(*) AS nodes, CAST(sum(size) AS BIGINT) AS sizes, CAST(sum(CASE WHEN size = 1 THEN 1 ELSE 0 END) AS BIGINT) AS leaves FROM (
SELECT 5 AS depth, 1 AS size FROM n UNION ALL SELECT 4, 1 + lines FROM o UNION ALL SELECT 3, 1 + below FROM c UNION ALL SELECT 2, 1 + coalesce(below, 0) FROM k
UNION ALL SELECT 1, 1 + coalesce(sum(1 + coalesce(k.below, 0)), 0) FROM e LEFT JOIN k ON k.parent = e.b WHERE e.b BETWEEN 1 AND 5 GROUP BY e.b
UNION ALL SELECT 0, 1 + (SELECT count(*) FROM e)) GROUP BY 1"""
)
def tree_depth_lineitem(spark, d):
    """Regions, nations, customers and suppliers, orders and lines: 76,631 nodes at sf0.01."""
    got = graphs.tree_functions(_hierarchy(spark, d, "lines"), 0, **S)
    return got.groupBy("depth").agg(F.count(F.lit(1)).alias("nodes"), F.sum("size").alias("sizes"), F.sum(F.col("is_leaf").cast("long")).alias("leaves"))


#: 25 leaves make a heap of 49 nodes: the leaves from left to right are 32 to 49, then 25 to 31.
_LEAVES = [*range(32, 50), *range(25, 32)]


def _heap(spark, values: DataFrame, product: bool) -> DataFrame:
    """The heap-shaped expression tree over (leaf 0 .. 24, value): sums, and products on every second level if asked."""
    inner = spark.createDataFrame(
        [(i, i // 2 if i > 1 else None, (i & 1) if i > 1 else None, "*" if product and i.bit_length() % 2 == 0 else "+") for i in range(1, 25)], "id long, parent long, side int, op string"
    ).select("*", F.lit(None).cast("long").alias("value"), F.lit(None).cast("long").alias("number"))
    at = spark.createDataFrame([(k, i, k + 1) for k, i in enumerate(_LEAVES)], "leaf long, id long, number long")
    leaves = values.join(F.broadcast(at), "leaf").select("id", F.floor(F.col("id") / 2).alias("parent"), (F.col("id") % 2).cast("int").alias("side"), F.lit(None).cast("string").alias("op"), "value", "number")
    return inner.unionByName(leaves)


def _heap_sql(values: str, product: bool, out: str) -> str:
    """Level by level up the heap, modulo the prime."""
    ctes = [f"l AS ({values})", f"n0 AS (SELECT CAST(list_extract({_LEAVES}, CAST(leaf + 1 AS INTEGER)) AS BIGINT) AS id, CAST(value % {graphs.PRIME} AS BIGINT) AS v FROM l)"]
    for k in range(1, 6):
        level = 6 - k
        lo, hi = 1 << (level - 1), 1 << level
        op = "*" if product and level % 2 == 0 else "+"
        ctes.append(
            f"n{k} AS (SELECT id, v FROM n{k - 1} WHERE id < {hi} UNION ALL SELECT a.id // 2, CAST((CAST(a.v AS HUGEINT) {op} b.v) % {graphs.PRIME} AS BIGINT) FROM n{k - 1} a JOIN n{k - 1} b ON b.id = a.id + 1 WHERE a.id >= {hi} AND a.id % 2 = 0 AND a.id // 2 >= {lo})"
        )
    return f"WITH {', '.join(ctes)} SELECT v AS {out} FROM n5 WHERE id = 1"


@query(_heap_sql("SELECT CAST(n_nationkey AS BIGINT) AS leaf, CAST(n_nationkey * 37 + 11 AS BIGINT) AS value FROM nation", True, "value"))
def contract_affine_tree(spark, d):
    leaves = t(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("leaf"), (F.col("n_nationkey") * 37 + 11).cast("long").alias("value"))
    v = graphs.contract_tree(_heap(spark, leaves, True), 25, seed=7)
    return spark.createDataFrame([(v,)], "value long")


_SALES = "SELECT CAST(c_nationkey AS BIGINT) AS leaf, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS value FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"


@query(_heap_sql(f"SELECT n.n AS leaf, coalesce(value, 0) AS value FROM generate_series(0, 24) n(n) LEFT JOIN ({_SALES}) ON leaf = n.n", False, "total"))
def contract_sales_tree(spark, d):
    sales = relational.release(
        relational.group_aggregate(
            relational.lookup_join(t(spark, d, "orders").select("o_custkey", "o_totalprice"), t(spark, d, "customer"), "o_custkey", "c_custkey", ["c_nationkey"], **S), ["c_nationkey"], {"value": ("sum", cents("o_totalprice"))}, **S
        )
    ).select(F.col("c_nationkey").cast("long").alias("_l"), F.pmod("value", F.lit(graphs.PRIME)).alias("_v"))
    leaves = spark.range(25).select(F.col("id").alias("leaf")).join(F.broadcast(sales), F.col("leaf") == F.col("_l"), "left").select("leaf", F.coalesce("_v", F.lit(0)).alias("value"))
    return spark.createDataFrame([(graphs.contract_tree(_heap(spark, leaves, False), 25, seed=7),)], "total long")


# -- graphs ---------------------------------------------------------------------------------------------------------


def _groups_as_edges(df: DataFrame, key: str, by: str) -> DataFrame:
    """An edge from each row to the next of its group, by an oblivious sort and a scan: what a group's rows have in common is left to the graph. Rows without a group are one."""
    h = F.sha2(F.coalesce(F.concat(F.lit("="), F.col(by)), F.lit("")), 256)
    rows = df.select(F.col(key).cast("long").alias("u"), F.substring(h, 1, 32).alias("h"))
    return relational.neighbour(rows, ["h"], ["u"], F.col("u"), "v", widths={"h": 32}, **S).filter("v IS NOT NULL").select("u", "v")


@query("SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS component FROM documents")
def cc_document_copies(spark, d):
    docs = t(spark, d, "documents").select("doc_id", F.sha2("text", 256).alias("h"))
    return graphs.connected_components(docs.select(F.col("doc_id").alias("id")), _groups_as_edges(docs, "doc_id", "h")).select(F.col("id").alias("doc_id"), "component")


@query("SELECT page_id, min(page_id) OVER (PARTITION BY regexp_extract(url, '://([^/]+)', 1)) AS component FROM pages")
def cc_page_hosts(spark, d):
    pages = t(spark, d, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("h"))
    return graphs.connected_components(pages.select(F.col("page_id").alias("id")), _groups_as_edges(pages, "page_id", "h")).select(F.col("id").alias("page_id"), "component")


def _supplies(spark, d):
    parts = t(spark, d, "part").count()
    edges = t(spark, d, "lineitem").filter("l_quantity >= 49").select(F.col("l_partkey").alias("u"), (F.col("l_suppkey") + parts).alias("v"))
    ids = t(spark, d, "part").select(F.col("p_partkey").alias("id")).union(t(spark, d, "supplier").select(F.col("s_suppkey") + parts))
    return ids, edges


_CC = """WITH RECURSIVE p AS (SELECT count(*) AS n FROM part), e AS (SELECT DISTINCT l_partkey AS u, l_suppkey + n AS v FROM lineitem, p WHERE l_quantity >= 49),
x AS (SELECT u, v FROM e UNION ALL SELECT v, u FROM e), ids AS (SELECT p_partkey AS id FROM part UNION ALL SELECT s_suppkey + n FROM supplier, p),
c(id, component) USING KEY (id) AS (SELECT id, id FROM ids UNION
SELECT x.v, min(a.component) FROM c a JOIN x ON x.u = a.id JOIN recurring.c b ON b.id = x.v WHERE a.component < b.component GROUP BY x.v)
SELECT id, component FROM c"""


@query(_CC)
def cc_supplier_part(spark, d):
    ids, edges = _supplies(spark, d)
    return graphs.connected_components(ids, edges)


@query(_CC)
def baseline_cc_stars(spark, d):
    ids, edges = _supplies(spark, d)
    got = star_components(edges, "u", "v")
    return ids.join(got, F.col("id") == F.col("node"), "left").select("id", F.coalesce("component", "id").alias("component"))


_COPIES = "SELECT n_nationkey::BIGINT AS id, min(n_nationkey::BIGINT) OVER (PARTITION BY n_regionkey) AS component FROM nation"


@query(_COPIES)
def cc_memory_steps(spark, d):
    """Nations linked to the next of their region: star hooking across tasks, none of it in one, until nothing moves."""
    n = t(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("id"), "n_regionkey")
    edges = relational.neighbour(n, ["n_regionkey"], ["id"], F.col("id"), "v", **S).filter("v IS NOT NULL").select(F.col("id").alias("u"), "v")
    return graphs.connected_components(n.select("id"), edges, tail=0, rounds="until_stable", **S)


_TRADE = """SELECT row_number() OVER (ORDER BY u, v) - 1 AS e, u, v, w FROM (
SELECT least(c_nationkey, s_nationkey)::BIGINT AS u, greatest(c_nationkey, s_nationkey)::BIGINT AS v, min(CAST(round(l_extendedprice * 100) AS BIGINT)) AS w
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey GROUP BY 1, 2)"""


@query(
    f"""WITH RECURSIVE e AS ({_TRADE}), r AS (SELECT *, row_number() OVER (ORDER BY w, e) AS k FROM e),
x AS (SELECT u, v, k FROM r UNION ALL SELECT v, u, k FROM r),
c(u, v, k, step) USING KEY (u, v) AS (SELECT u, v, k, 0 FROM x UNION
SELECT a.u, b.v, min(greatest(a.k, b.k)), max(a.step) + 1 FROM recurring.c a JOIN x b ON a.v = b.u AND a.u <> b.v LEFT JOIN recurring.c o ON o.u = a.u AND o.v = b.v
WHERE o.k IS NULL OR greatest(a.k, b.k) < o.k GROUP BY a.u, b.v)
SELECT r.e, r.u, r.v, r.w FROM r JOIN c ON c.u = r.u AND c.v = r.v AND c.k = r.k"""
)
def msf_nation_trade(spark, d):
    return graphs.min_spanning_forest(t(spark, d, "nation").select(F.col("n_nationkey").alias("id")), _trade(spark, d)).select("e", "u", "v", "w")


@query(_ORACLES["msf_nation_trade"])
def baseline_msf_kruskal(spark, d):
    return baselines.spanning_forest(_trade(spark, d))


def _trade(spark, d) -> DataFrame:
    """The least line price between each two nations, prepared in the open."""
    line = t(spark, d, "lineitem").select("l_orderkey", "l_suppkey", "l_extendedprice").join(t(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    line = line.join(t(spark, d, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(t(spark, d, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    line = line.filter("c_nationkey <> s_nationkey").groupBy(F.least("c_nationkey", "s_nationkey").cast("long").alias("u"), F.greatest("c_nationkey", "s_nationkey").cast("long").alias("v"))
    return materialise(dense_positions(line.agg(F.min(cents("l_extendedprice")).alias("w")), [F.col("u"), F.col("v")], "e"), "trade")


@query()
def msf_embeddings_knn(spark, d):
    """The lightest forest of the graph that joins each embedding to its five nearest others; squared distances in whole millionths. Its edges: every block of rows against all."""
    emb = t(spark, d, "embeddings").select("vec_id", "embedding")
    size = 1024
    n = emb.count()
    table = materialise(numbered(emb, "_at").withColumn("_block", F.floor(F.col("_at") / size)), "vectors")
    blocks = max(1, -(-n // size))
    pairs = table.withColumn("_against", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select("vec_id", "embedding", F.lit(0).alias("side"), (F.col("_block") * blocks + F.col("_against")).alias("cell"))
    others = table.withColumn("_against", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select("vec_id", "embedding", F.lit(1).alias("side"), (F.col("_against") * blocks + F.col("_block")).alias("cell"))

    def nearest(cell):
        import pandas as pd

        mine, all_ = (cell[cell["side"] == i] for i in (0, 1))
        a, b = (np.stack(x["embedding"].to_numpy()).astype(np.float64) for x in (mine, all_))
        dist = np.rint(np.maximum((a**2).sum(1)[:, None] + (b**2).sum(1)[None, :] - 2 * a @ b.T, 0) * 1e6).astype(np.int64)
        ids, to = mine["vec_id"].to_numpy(), all_["vec_id"].to_numpy()
        dist[ids[:, None] == to[None, :]] = np.iinfo(np.int64).max
        fifth = min(5, len(to)) - 1
        row, col = np.nonzero(dist <= np.partition(dist, fifth, axis=1)[:, fifth : fifth + 1])  # five of each row, and ties
        u, v, w = ids[row], to[col], dist[row, col]
        by = np.lexsort((v, w, row))
        row, u, v, w = row[by], u[by], v[by], w[by]
        keep = (np.arange(len(row)) - np.searchsorted(row, row) < 5) & (w < np.iinfo(np.int64).max)
        return pd.DataFrame({"u": u[keep], "v": v[keep], "w": w[keep]})

    from pyspark.sql import Window

    near = pairs.unionByName(others).groupBy("cell").applyInPandas(nearest, "u long, v long, w long")
    near = near.withColumn("_r", F.row_number().over(Window.partitionBy("u").orderBy("w", "v"))).filter("_r <= 5")
    edges = near.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "w").groupBy("u", "v").agg(F.min("w").alias("w"))
    edges = materialise(dense_positions(edges, [F.col("u"), F.col("v")], "e"), "knn")
    return graphs.min_spanning_forest(emb.select(F.col("vec_id").alias("id")), edges).select("e", "u", "v", "w")


# -- relational -----------------------------------------------------------------------------------------------------


@query(
    """SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS DOUBLE) AS sum_qty, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS sum_cents,
count(*) AS n, max(l_discount) AS most_discount FROM lineitem GROUP BY 1, 2"""
)
def group_agg_pricing(spark, d):
    df = t(spark, d, "lineitem").select("l_returnflag", "l_linestatus", "l_quantity", "l_extendedprice", "l_discount")
    aggs = {"sum_qty": ("sum", F.col("l_quantity")), "sum_cents": ("sum", cents("l_extendedprice")), "n": ("count", F.lit(1)), "most_discount": ("max", F.col("l_discount"))}
    return relational.release(relational.group_aggregate(df, ["l_returnflag", "l_linestatus"], aggs, widths=NARROW, **S))


@query(_ORACLES["group_agg_pricing"])
def baseline_group_agg(spark, d):
    aggs = {"sum_qty": F.sum("l_quantity"), "sum_cents": F.sum(cents("l_extendedprice")), "n": F.count(F.lit(1)), "most_discount": F.max("l_discount")}
    return baselines.plain_group(t(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"], aggs)


_CUST = "SELECT c_mktsegment AS seg, n_regionkey AS reg, CAST(round(c_acctbal * 100) AS BIGINT) AS c FROM customer JOIN nation ON c_nationkey = n_nationkey"


def _segments(spark, d):
    df = relational.public_join(t(spark, d, "customer"), t(spark, d, "nation"), "c_nationkey", "n_nationkey", ["n_regionkey"])
    return df.select(F.col("c_mktsegment").alias("seg"), F.col("n_regionkey").alias("reg"), cents("c_acctbal").alias("c"))



def _totals():
    return {"n": ("count", F.lit(1)), "total": ("sum", F.col("c"))}


def _sets_sql(how: str) -> str:
    return f"SELECT seg, reg, count(*) AS n, CAST(sum(c) AS BIGINT) AS total FROM ({_CUST}) GROUP BY {how}"


def _sets(spark, d, sets):
    return relational.release(relational.grouping_sets(_segments(spark, d), sets, _totals(), **S)).select("seg", "reg", "n", "total")


@query(_sets_sql("ROLLUP (seg, reg)"))
def rollup_segment_region(spark, d):
    return _sets(spark, d, relational.rollup(["seg", "reg"]))


@query(_sets_sql("CUBE (seg, reg)"))
def cube_segment_region(spark, d):
    return _sets(spark, d, relational.cube(["seg", "reg"]))


@query(_sets_sql("GROUPING SETS ((seg), (reg))"))
def grouping_sets_segment_region(spark, d):
    return _sets(spark, d, [["seg"], ["reg"]])


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def topk_orders(spark, d):
    return relational.top_k(_orders(spark, d), 20, _PRICE, **S).select("o_orderkey", "o_totalprice")


@query("SELECT DISTINCT p_brand, p_type FROM part")
def distinct_brand_type(spark, d):
    return relational.release(relational.distinct(t(spark, d, "part").select("p_brand", "p_type"), **S))


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
def semi_customers_with_f(spark, d):
    f = t(spark, d, "orders").filter("o_orderstatus = 'F'").select("o_custkey")
    return relational.release(relational.lookup_join(t(spark, d, "customer").select("c_custkey"), f, "c_custkey", "o_custkey", [], "semi", **S))


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
def anti_customers_with_f(spark, d):
    f = t(spark, d, "orders").filter("o_orderstatus = 'F'").select("o_custkey")
    return relational.release(relational.lookup_join(t(spark, d, "customer").select("c_custkey"), f, "c_custkey", "o_custkey", [], "anti", **S))


def _nations(spark, d):
    return t(spark, d, "customer").filter("c_acctbal > 9000").select(F.col("c_nationkey").alias("k")), t(spark, d, "supplier").filter("s_acctbal > 5000").select(F.col("s_nationkey").alias("k"))


for _kind, _word in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):
    query(f"SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 9000 {_word} SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000", f"{_kind}_nations")(
        lambda spark, d, kind=_kind: relational.release(relational.set_operation(*_nations(spark, d), kind, **S))
    )


@query(
    """SELECT e.event_id, p.event_id AS purchase FROM events e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p
ON e.user_id = p.user_id AND e.ts >= p.ts"""
)
def asof_last_purchase(spark, d):
    ev = t(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    right = ev.filter("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase"))
    return relational.as_of_join(ev.select("event_id", "user_id", "ts"), right, "user_id", "ts", ["purchase"], **S).select("event_id", "purchase")


@query("SELECT o_orderkey, row_number() OVER w AS row_number, rank() OVER v AS rank, dense_rank() OVER v AS dense_rank FROM orders WINDOW w AS (PARTITION BY o_orderstatus ORDER BY o_orderpriority, o_orderkey), v AS (PARTITION BY o_orderstatus ORDER BY o_orderpriority)")
def rank_window_suite(spark, d):
    df = t(spark, d, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority")
    rows = relational.window_ranks(df, ["o_orderstatus"], ["o_orderpriority"], **S).select("o_orderkey", "rank", "dense_rank")
    full = relational.window_ranks(df, ["o_orderstatus"], ["o_orderpriority", "o_orderkey"], **S).select("o_orderkey", "row_number")
    return relational.lookup_join(full, rows, "o_orderkey", "o_orderkey", ["rank", "dense_rank"], "left", **S).select("o_orderkey", "row_number", "rank", "dense_rank")


@query(
    """SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS second, first_value(event_id) OVER f AS first_value, last_value(event_id) OVER f AS last_value
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id), f AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"""
)
def window_neighbours(spark, d):
    df, at = t(spark, d, "events").select("user_id", "ts", "event_id"), ["ts", "event_id"]
    df = relational.neighbour(df, ["user_id"], at, F.col("event_id"), "before", **S)
    df = relational.neighbour(materialise(df, "lag"), ["user_id"], at, F.col("event_id"), "second", -2, **S)
    return relational.first_last(materialise(df, "lead"), ["user_id"], at, F.col("event_id"), **S).select("event_id", "before", "second", "first_value", "last_value")


@query(
    """SELECT event_id, CAST(sum(CAST(round("value" * 100) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS near,
CAST(ntile(4) OVER w AS INTEGER) AS ntile, round(percent_rank() OVER w, 9) AS percent_rank, round(cume_dist() OVER w, 9) AS cume_dist FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"""
)
def window_frames(spark, d):
    df, at = t(spark, d, "events").select("user_id", "ts", "event_id", cents("value").alias("c")), ["ts", "event_id"]
    df = relational.frame_sum(df, ["user_id"], at, F.col("c"), "near", 3, 1, **S)
    df = relational.window_shares(materialise(df, "frames"), ["user_id"], at, 4, **S)
    return df.select("event_id", "near", "ntile", F.round("percent_rank", 9).alias("percent_rank"), F.round("cume_dist", 9).alias("cume_dist"))


@query("SELECT share, (SELECT o_totalprice FROM (SELECT o_totalprice, row_number() OVER (ORDER BY o_totalprice) - 1 AS r FROM orders) WHERE r = CAST(floor(share * ((SELECT count(*) FROM orders) - 1)) AS BIGINT) LIMIT 1) AS o_totalprice FROM (VALUES (0.0::DOUBLE), (0.25), (0.5), (1.0)) q(share)")
def quantiles_orders(spark, d):
    return relational.quantiles(t(spark, d, "orders"), "o_totalprice", [0.0, 0.25, 0.5, 1.0], **S)


@query("SELECT n_nationkey, s_suppkey FROM (SELECT n_nationkey::BIGINT AS n_nationkey FROM nation) n FULL JOIN (SELECT s_suppkey % 40 AS k, min(s_suppkey) AS s_suppkey FROM supplier GROUP BY 1) s ON n_nationkey = k WHERE true")
def outer_join_nations(spark, d):
    s = t(spark, d, "supplier").groupBy((F.col("s_suppkey") % 40).alias("k")).agg(F.min("s_suppkey").alias("s_suppkey"))
    n = t(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("k"), F.col("n_nationkey").cast("long").alias("n_nationkey"))
    return relational.release(relational.lookup_join(n, s, "k", "k", ["s_suppkey"], "outer", **S)).select("n_nationkey", "s_suppkey")


@query("SELECT o_orderkey, CAST(floor(o_totalprice / 5000) AS BIGINT) AS band FROM orders WHERE true")
def range_join_price_bands(spark, d):
    """Each order in the price band that it lies in, of bands of 5,000 up to the greatest price."""
    top = t(spark, d, "orders").agg(F.max("o_totalprice")).first()[0]
    bands = spark.range(int(top // 5000) + 1).select(F.col("id").alias("band"), (F.col("id") * 5000.0).alias("low"), ((F.col("id") + 1) * 5000.0).alias("high"))
    return relational.range_join(_orders(spark, d), bands, "o_totalprice", "low", "high", ["band"], **S).select("o_orderkey", "band")


@query("SELECT s_suppkey, n_name FROM supplier JOIN nation ON s_suppkey % 25 > n_nationkey AND n_regionkey = 1")
def theta_join_supplier_nation(spark, d):
    nations = t(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey")
    return relational.release(relational.theta_join(t(spark, d, "supplier").select("s_suppkey"), nations, (F.col("s_suppkey") % 25 > F.col("n_nationkey")) & (F.col("n_regionkey") == 1))).select("s_suppkey", "n_name")


@query(
    """SELECT c_nationkey, count(*) FILTER (c_mktsegment = 'BUILDING') AS "BUILDING_n", count(*) FILTER (c_mktsegment = 'MACHINERY') AS "MACHINERY_n" FROM customer GROUP BY 1 HAVING count(*) FILTER (c_mktsegment = 'BUILDING') > 2"""
)
def pivot_having_segments(spark, d):
    got = relational.pivot(t(spark, d, "customer").select("c_nationkey", "c_mktsegment"), ["c_nationkey"], "c_mktsegment", ["BUILDING", "MACHINERY"], {"n": ("count", F.lit(1))}, **S)
    return relational.release(relational.having(got, F.col("BUILDING_n") > 2))


@query(
    """SELECT user_id, count(DISTINCT event_type) AS kinds, round(var_samp(c), 4) AS spread, arg_max(event_id, ts) AS latest FROM (SELECT *, CAST(round("value" * 100) AS BIGINT) AS c FROM events) GROUP BY 1"""
)
def group_agg_more(spark, d):
    df = t(spark, d, "events").select("user_id", "event_type", "ts", "event_id", cents("value").alias("c"))
    aggs = {"kinds": ("count_distinct", F.col("event_type")), "spread": ("var", F.col("c")), "latest": ("max_by", F.struct(F.col("ts").alias("by"), F.col("event_id").alias("value")))}
    return relational.release(relational.group_aggregate(df, ["user_id"], aggs, **S)).select("user_id", "kinds", F.round("spread", 4).alias("spread"), "latest")


_REV = "CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT)"


@query(
    f"""SELECT l_orderkey, {_REV} AS cents, o_orderdate FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
WHERE c_mktsegment = 'BUILDING' AND l_returnflag = 'R' GROUP BY l_orderkey, o_orderdate ORDER BY cents DESC, l_orderkey LIMIT 10"""
)
def q3_like(spark, d):
    cust = t(spark, d, "customer").select("c_custkey", "c_mktsegment")
    orders = relational.lookup_join(t(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate"), cust, "o_custkey", "c_custkey", ["c_mktsegment"], **S)
    line = relational.lookup_join(t(spark, d, "lineitem").select("l_orderkey", "l_extendedprice", "l_returnflag"), materialise(relational.release(orders), "o"), "l_orderkey", "o_orderkey", ["o_orderdate", "c_mktsegment"], **S)
    line = relational.where(line, (F.col("c_mktsegment") == "BUILDING") & (F.col("l_returnflag") == "R"))
    sums = relational.group_aggregate(line, ["l_orderkey", "o_orderdate"], {"cents": ("sum", cents("l_extendedprice"))}, **S)
    return relational.release(relational.top_k(materialise(sums, "q3"), 10, [Key("cents", False), Key("l_orderkey")], **S)).select("l_orderkey", "cents", "o_orderdate")


@query(
    f"""SELECT n_name, {_REV} AS cents FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
JOIN nation ON s_nationkey = n_nationkey WHERE c_nationkey = s_nationkey GROUP BY 1"""
)
def q5_like(spark, d):
    orders = relational.release(relational.lookup_join(t(spark, d, "orders").select("o_orderkey", "o_custkey"), t(spark, d, "customer").select("c_custkey", "c_nationkey"), "o_custkey", "c_custkey", ["c_nationkey"], **S))
    line = relational.lookup_join(t(spark, d, "lineitem").select("l_orderkey", "l_suppkey", "l_extendedprice"), materialise(orders, "o"), "l_orderkey", "o_orderkey", ["c_nationkey"], **S)
    line = relational.release(line)
    line = relational.lookup_join(materialise(line, "l"), t(spark, d, "supplier").select("s_suppkey", "s_nationkey"), "l_suppkey", "s_suppkey", ["s_nationkey"], **S)
    line = relational.where(line, F.col("c_nationkey") == F.col("s_nationkey"))
    sums = relational.release(relational.group_aggregate(line, ["s_nationkey"], {"cents": ("sum", cents("l_extendedprice"))}, **S))
    return relational.public_join(sums, t(spark, d, "nation"), "s_nationkey", "n_nationkey", ["n_name"]).select("n_name", "cents")


@query(
    f"""SELECT c_custkey, c_name, {_REV} AS cents, n_name FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey
WHERE l_returnflag = 'R' GROUP BY 1, 2, 4 ORDER BY cents DESC, c_custkey LIMIT 20"""
)
def q10_like(spark, d):
    line = relational.lookup_join(t(spark, d, "lineitem").select("l_orderkey", "l_extendedprice", "l_returnflag"), t(spark, d, "orders").select("o_orderkey", "o_custkey"), "l_orderkey", "o_orderkey", ["o_custkey"], **S)
    line = relational.where(line, F.col("l_returnflag") == "R")
    sums = materialise(relational.group_aggregate(line, ["o_custkey"], {"cents": ("sum", cents("l_extendedprice"))}, **S), "q10")
    top = materialise(relational.release(relational.top_k(sums, 20, [Key("cents", False), Key("o_custkey")], **S)).drop("pos"), "q10")
    cust = t(spark, d, "customer").select("c_custkey", "c_name", "c_nationkey")
    got = relational.release(relational.lookup_join(top, cust, "o_custkey", "c_custkey", ["c_name", "c_nationkey"], **S))
    return relational.public_join(got, t(spark, d, "nation"), "c_nationkey", "n_nationkey", ["n_name"]).select(F.col("o_custkey").alias("c_custkey"), "c_name", "cents", "n_name")


@query("SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY 1")
def json_prop_totals(spark, d):
    df = t(spark, d, "events").select("event_type", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return relational.release(relational.group_aggregate(df, ["event_type"], {"total": ("sum", F.col("k"))}, **S))


@query("SELECT s_suppkey, c_custkey FROM supplier JOIN customer ON s_nationkey = c_nationkey WHERE s_acctbal > 5000 AND c_acctbal > 9000")
def expand_join_same_nation(spark, d):
    left = t(spark, d, "supplier").filter("s_acctbal > 5000").select("s_suppkey", F.col("s_nationkey").alias("k"))
    right = t(spark, d, "customer").filter("c_acctbal > 9000").select("c_custkey", F.col("c_nationkey").alias("k"))
    both = left.groupBy("k").agg(F.count(F.lit(1)).alias("n")).join(right.groupBy("k").agg(F.count(F.lit(1)).alias("m")), "k")
    bound = both.agg(F.sum(F.col("n") * F.col("m"))).first()[0] or 0  # in the open: the number of matches, which the release below shows anyway
    return relational.release(relational.expand_join(left, right, "k", params.power_of_two(max(1, bound)), **S)).select("s_suppkey", "c_custkey")


# -- streams --------------------------------------------------------------------------------------------------------


def _stream(spark, d, columns: list[str], fn) -> None:
    """Events in three micro-batches of one file each through ``fn``, each padded to a third of all rows."""
    from .plans.shared import shared_dir
    import uuid

    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    events = t(spark, d, "events").select(columns)
    rows = -(-events.count() // 3)
    third = F.floor(F.col("_i") / max(rows, 1)).cast("int")
    dense_positions(events, [F.col("ts")], "_i").repartitionById(3, third).drop("_i").write.parquet(path)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    q = streaming.oblivious_foreach(stream, rows, fn).option("checkpointLocation", f"{path}-progress").trigger(availableNow=True).start()
    q.awaitTermination()


@query("SELECT date_trunc('hour', ts)::TIMESTAMP AS window_start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling_counts(spark, d):
    counts = streaming.TumblingCounts("ts", "event_type", "hour", **S)
    _stream(spark, d, ["ts", "event_type", "event_id"], counts)
    return counts.table


@query(
    """SELECT to_timestamp(floor(epoch(ts) / 21600) * 21600 - i * 21600)::TIMESTAMPTZ AT TIME ZONE 'UTC' AS window_start, event_type, count(*) AS n
FROM events, generate_series(0, 3) s(i) GROUP BY 1, 2"""
)
def stream_sliding_counts(spark, d):
    """Windows of a day that begin every six hours."""
    counts = streaming.SlidingCounts("ts", "event_type", 86400, 21600, **S)
    _stream(spark, d, ["ts", "event_type", "event_id"], counts)
    return counts.table


@query('SELECT u.u AS user_id, CAST(coalesce(sum(CAST(round("value" * 100) AS BIGINT)), 0) AS BIGINT) AS val FROM generate_series(0, greatest(149, (SELECT max(user_id) FROM events))) u(u) LEFT JOIN events ON user_id = u.u GROUP BY 1')
def stream_state_balances(spark, d):
    state = streaming.BalanceState(_user_cells(spark, d), "user_id", "cents", **S)

    def step(batch, i):
        state(batch.withColumn("cents", cents("value")), i)

    _stream(spark, d, ["ts", "user_id", "value"], step)
    return state.cells.select(F.col("addr").alias("user_id"), "val")


# -- costs and views ------------------------------------------------------------------------------------------------

#: The rows of the comparison tables as formulas of lg n, for SQL; fixed values.
_L, _LL = "log2(n)", "log2(log2(n))"
_QS = "(n / b * log2(n) / log2(m))"
_W = f"(n * {_L})"
_BEST = f"{_W}, {_L} * {_LL}, {_QS}, true"
_LIST = f"{_W}, {_L} ** 2 * {_LL}, {_QS}, true"
_TABLES = {
    "T1": [
        ("sort", "insecure", "false", _BEST), ("sort", "ours", "true", _BEST), ("list ranking", "insecure", "false", _LIST), ("list ranking", "ours", "true", _LIST),
        ("Euler tour, tree functions", "insecure", "false", _LIST), ("Euler tour, tree functions", "ours", "true", _LIST),
        ("tree contraction", "insecure", "false", f"{_W}, {_L} ** 3 * {_LL}, {_QS}, true"), ("tree contraction", "ours", "true", _LIST),
        *((what, who, flag, f"n * {_L} ** 2, {_L} ** {power} * {_LL}, {_QS} * {_L}, true") for what in ("connected components", "spanning forest") for who, flag, power in (("insecure", "false", 3), ("ours", "true", 2))),
    ],
    "T2": [
        ("aggregate, propagate", "earlier", "true", f"n, {_L} ** 2, n / b, false"), ("aggregate, propagate", "ours", "true", f"n, {_L}, n / b, false"),
        ("sort, send-receive", "earlier, network", "true", f"{_W}, {_L} ** 2, {_W}, false"), ("sort, send-receive", "earlier, cache-agnostic", "true", f"{_W} * {_LL} ** 2, sqrt(n), {_QS}, false"),
        ("sort, send-receive", "ours", "true", _BEST), ("memory step, small", "earlier", "true", "s * log2(s) ** 2, log2(s) ** 2, s * log2(s), false"),
        ("memory step, small", "ours", "true", "s * log2(s), log2(s) * log2(log2(s)), s / b * greatest(1, log2(s) / log2(m)), true"),
        ("memory step, large", "earlier", "true", "p * log2(s) ** 2, log2(s) ** 2 * log2(log2(s)), p * log2(s) ** 2, true"),
        ("memory step, large", "ours", "true", "p * log2(s) ** 2, log2(s) * log2(log2(s)), log2(s) * (p / b * greatest(1, log2(p) / log2(m)) + p * log2(s) / log2(b)), true"),
    ],
    "T3": [
        ("permute", "bin routing", "true", _BEST), ("sort a permuted array", "pivot routing", "false", _BEST), ("sort", "permute, then compare", "true", _BEST),
        ("sort", "bitonic, fork-join", "true", f"n * {_L} ** 2, {_L} ** 2 * {_LL}, {_QS} * log2(n / m), true"), ("sort", "bitonic, naive", "true", f"n * {_L} ** 2, {_L} ** 3, n / b * {_L} ** 2, false"),
        ("sort", "two passes, practical", "true", f"{_W} * {_LL}, {_L} ** 2 * {_LL}, {_QS}, true"), ("sort", "two passes, optimal work", "true", f"{_W}, {_L} ** 2 * {_LL}, {_QS}, true"),
    ],
}


#: Lengths that the bounds are evaluated at: records, processors and cells, with the least that the formulas take.
_LENGTHS = (("lineitem", "l_orderkey", 8192), ("supplier", "s_suppkey", 64), ("part", "p_partkey", 64))


def _bounds_sql(name: str) -> str:
    kinds = ("VARCHAR", "VARCHAR", "BOOLEAN", "DOUBLE", "DOUBLE", "DOUBLE", "BOOLEAN")
    names = ("task", "method", "oblivious", "work", "span", "misses", "hides_loglog")
    parts = " UNION ALL ".join(f"SELECT '{what}', '{who}', {flag}, {costs} FROM v" for what, who, flag, costs in _TABLES[name])
    cols = ", ".join(f"round(CAST({c} AS DOUBLE), 3) AS {c}" if k == "DOUBLE" else f"CAST({c} AS {k}) AS {c}" for c, k in zip(names, kinds))
    n, p, s = (f"greatest({least}, (SELECT count({c}) FROM {t_}))::DOUBLE" for t_, c, least in _LENGTHS)
    return f"WITH v AS (SELECT {n} AS n, 4096.0::DOUBLE AS m, 16.0::DOUBLE AS b, {p} AS p, {s} AS s) SELECT {cols} FROM ({parts}) x({', '.join(names)})"


def _bounds(spark, d, name: str) -> DataFrame:
    n, p, s = (float(max(least, t(spark, d, table).agg(F.count(c)).first()[0])) for table, c, least in _LENGTHS)
    return bounds.table(spark, name, n, 4096, 16, p, s).withColumns({c: F.round(c, 3) for c in ("work", "span", "misses")})


for _name in ("T1", "T2", "T3"):
    query(_bounds_sql(_name), f"bounds_{_name}")(lambda spark, d, name=_name: _bounds(spark, d, name))


def _dealt(df: DataFrame) -> DataFrame:
    """Rows dealt to as many tasks as run at once, for kernels that take longer than reading."""
    ship_package(df.sparkSession)
    return df.repartition(max(df.sparkSession.sparkContext.defaultParallelism, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))


def _in_blocks(df: DataFrame, sizes: tuple[int, ...], fn, schema: str) -> DataFrame:
    """What ``fn(blocks, n)`` gives, once each, for the one column of ``df`` in blocks of each of the sizes n, a row a block: tasks read the table and run the kernels.

    What is left over fills a block up with numbers beyond the greatest.
    """
    most, names = max(sizes), [f.split()[0] for f in schema.split(", ")]

    def full(x: np.ndarray, n: int) -> np.ndarray:
        more = -len(x) % n
        return np.concatenate((x, x.max(initial=0) + 1 + np.arange(more, dtype=np.uint64))).reshape(-1, n)

    def kernel(batches):
        held, got = np.empty(0, np.uint64), set()

        def take(x):
            for n in sizes:
                got.update(fn(full(x, n), n))

        for batch in batches:
            held = np.concatenate((held, batch.column(0).fill_null(0).to_numpy(zero_copy_only=False).astype(np.uint64)))
            ready = len(held) // most * most
            if ready:
                take(held[:ready])
                held = held[ready:]
        if len(held):
            take(held)
        if got:
            yield pa.record_batch([pa.array(c) for c in zip(*sorted(got))], names=names)

    return _dealt(df).mapInArrow(kernel, schema).distinct()


def _sorted_view(blocks: np.ndarray, n: int, recursive: bool) -> tuple[tuple, K.Meter]:
    """One block's own view of the network that sorts all the blocks side by side, and what it counts for them."""
    meter, r = K.Meter(trace=[]), len(blocks)
    s = K.Slab(blocks.reshape(-1, 1).copy(), np.ones(blocks.size, bool), np.zeros((blocks.size, 1), np.uint8))
    K.bitonic_sort_block(s, n, meter, recursive=recursive)
    if (s.words.reshape(r, n) != np.sort(blocks, axis=1)).any():
        raise AssertionError("a block isn't sorted")
    return tuple((e[0], e[1] // r, *e[2:]) if e[0] == "exchange" else e for e in meter.trace), meter


@lru_cache(maxsize=16)
def _replayed(view: tuple) -> int:
    return bounds.CacheSim(256, 8).replay(trace.addresses(list(view)))


@query("SELECT CAST(pow(2, k) AS BIGINT) AS n, CAST(pow(2, k) / 8 * k * (k + 1) / 2 AS BIGINT) AS layer_by_layer, true AS recursive_fewer FROM generate_series(9, 11) t(k)")
def cost_cache_replay(spark, d):
    """Misses over the kernels' own addresses on blocks of the lines' parts, with a cache of 256 places in lines of 8: a scan a layer, and fewer for the recursive order."""
    def count(blocks, n):
        plain, recursive = (_replayed(_sorted_view(blocks, n, x)[0]) for x in (False, True))
        return [(n, plain, recursive < plain)]

    return _in_blocks(t(spark, d, "lineitem").select(F.col("l_partkey").cast("long")), (512, 1024, 2048), count, "n long, layer_by_layer long, recursive_fewer boolean")


@query()
def cost_practical_constants(spark, d):
    """Comparators of the two-pass sort's first pass over n log n loglog n, counted by running the network on blocks of the customers' balances."""
    count = lambda blocks, n: {tuple(bounds.practical_constants(n, b).values()) for b in blocks}
    return _in_blocks(t(spark, d, "customer").select(cents("c_acctbal")), (256, 1024, 4096), count, "n long, work double, slots double")


@query("SELECT * FROM (VALUES ('chi_squared', true), ('fixed_points', true), ('serial', true), ('load_and_order', true)) t(measure, as_uniform)")
def permute_uniformity(spark, d):
    """Permutations of each 32 orders, 400 at least: place by origin, fixed points, neighbours, and whether bin loads, which show, say anything about the order."""
    keys = _dealt(t(spark, d, "orders").select("o_orderkey"))
    got = trace.table_uniformity(keys, 32, 400, params.from_length(32))
    fine = {"chi_squared": abs(got["chi_squared"]) < 4, "fixed_points": abs(got["fixed_points"] - 1) < 0.2, "serial": abs(got["serial"] + 1 / 32) < 0.05, "load_and_order": abs(got["load_and_order"]) < 0.2}
    return spark.createDataFrame(list(fine.items()), "measure string, as_uniform boolean")


@query("SELECT true AS same_distribution, true AS equal_under_equal_coins")
def view_randomised(spark, d):
    """The loads that a permutation shows, over many coins, for two different inputs: of one distribution, and equal for equal coins."""
    col = t(spark, d, "customer").select(F.col("c_custkey").alias("a"), cents("c_acctbal").alias("b")).toPandas()
    p = params.from_length(len(col))
    a = [trace.kernel_permutation(col["a"].to_numpy(), p, s)[1] for s in range(60)]
    b = [trace.kernel_permutation(np.abs(col["b"].to_numpy()), p, s + 1000)[1] for s in range(60)]
    same = trace.same_distribution(np.concatenate(a), np.concatenate(b)) < 1.95
    equal = all((trace.kernel_permutation(np.abs(col["b"].to_numpy()), p, s)[1] == a[s]).all() for s in range(5))
    return spark.createDataFrame([(bool(same), bool(equal))], "same_distribution boolean, equal_under_equal_coins boolean")


@query("SELECT CAST(pow(2, k) AS BIGINT) AS n, CAST(pow(2, k) * k * (k + 1) / 4 AS BIGINT) AS comparators, CAST(k * (k + 1) / 2 AS BIGINT) AS layers FROM generate_series(1, 10) t(k)")
def cost_bitonic_counts(spark, d):
    """Counted by running the network on blocks of the lines' parts, beside the closed form in SQL."""

    def count(blocks, n):
        _, m = _sorted_view(blocks, n, False)
        return [(n, m.comparators // len(blocks), m.layers)]

    return _in_blocks(t(spark, d, "lineitem").select(F.col("l_partkey").cast("long")), tuple(1 << k for k in range(1, 11)), count, "n long, comparators long, layers long")


_COUNTED = (("lineitem", "l_extendedprice"), ("orders", "o_totalprice"), ("events", "value"), ("customer", "c_acctbal"), ("part", "p_retailprice"), ("supplier", "s_acctbal"))
_ROWS = " UNION ALL ".join(f'SELECT count("{c}") FROM {table}' for table, c in _COUNTED)


@query(
    f"""WITH a AS (SELECT n, log2(n) AS l, greatest(16, pow(2, ceil(log2(log2(n) * log2(n))))) AS z FROM (SELECT greatest(4, n) AS n FROM ({_ROWS}) r(n))),
b AS (SELECT n, l, z, greatest(0, ceil(log2(2 * n / z))) AS bits, greatest(1, round(log2(l))) AS radix FROM a),
c AS (SELECT n, z, pow(2, bits) AS beta, pow(2, radix) AS gamma, ceil(bits / radix) AS layers, ceil(greatest(16, ceil(l * log2(l))) / 64) AS tag_words, z * pow(2, bits) / n AS over FROM b)
SELECT n, CAST(z AS BIGINT) AS z, CAST(beta AS BIGINT) AS beta, CAST(gamma AS BIGINT) AS gamma, CAST(layers AS BIGINT) AS layers, CAST(tag_words AS BIGINT) AS tag_words, CAST(z * beta AS BIGINT) AS slots,
round(least(0, log10(greatest(1, beta * layers)) - n / beta * (over * ln(over) - over + 1) / ln(10)), 3) AS log10_overflow FROM c"""
)
def cost_router_layers(spark, d):
    """Parameters of the router for the lengths of the tables: slots of a bin, bins, ways and layers, words of a tag, slots in all, and the bound on a bin's overflow."""
    ps = [params.from_length(max(4, t(spark, d, table).agg(F.count(c)).first()[0])) for table, c in _COUNTED]
    rows = [(p.n, p.z, p.beta, p.gamma, p.layers, p.tag_words, p.slots, params.log10_overflow(p)) for p in ps]
    got = spark.createDataFrame(rows, "n long, z long, beta long, gamma long, layers long, tag_words long, slots long, log10_overflow double")
    return got.withColumn("log10_overflow", F.round("log10_overflow", 3))


@query("SELECT m AS method, true AS views_equal FROM (VALUES ('bitonic sort'), ('bitonic sort, recursive'), ('layered router'), ('recursive router')) t(m)")
def view_equal_inputs(spark, d):
    """Kernel traces and the places that they touch, over two columns of the whole table, some blocks side by side, and the one simulated from the length alone."""
    p, methods = params.from_length(1024), ("bitonic sort", "bitonic sort, recursive", "layered router", "recursive router")
    alone = {m: trace.simulate_view(m, 1024, p) for m in methods}

    def kernel(batches):
        held, same = np.empty((2, 0), np.uint64), dict.fromkeys(methods, True)

        def look(x):
            for m in methods:
                same[m] = same[m] and trace.kernel_view(m, x, p) == alone[m]

        for batch in batches:
            held = np.concatenate((held, [c.fill_null(0).to_numpy(zero_copy_only=False).astype(np.uint64) for c in batch.columns]), axis=1)
            ready = held.shape[1] // 1024 * 1024
            if ready >= 16 * 1024:
                look(held[:, :ready].reshape(-1, 1024))
                held = held[:, ready:]
        if held.shape[1] >= 1024:
            look(held[:, : held.shape[1] // 1024 * 1024].reshape(-1, 1024))
        if held.shape[1] % 1024:
            look(np.stack([np.resize(c, 1024) for c in held[:, held.shape[1] // 1024 * 1024 :]]))
        yield pa.record_batch([pa.array(list(same)), pa.array(list(same.values()))], names=["method", "same"])

    blocks = t(spark, d, "lineitem").select(F.col("l_partkey").cast("long").alias("a"), F.col("l_suppkey").cast("long").alias("b"))
    got = _dealt(blocks).mapInArrow(kernel, "method string, same boolean")
    return got.groupBy("method").agg(F.bool_and("same").alias("views_equal"))


def queries() -> dict:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_ORACLES)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """A secret permutation and sort of the lines, a scan per flag and status, and one row a group."""
    lines = sorts.oblivious_sort(t(spark, d, "lineitem").select(LINE), LINE, widths=NARROW, small=0, **S)
    aggs = {"n": ("count", F.lit(1)), "sum_qty": ("sum", F.col("l_quantity")), "sum_cents": ("sum", cents("l_extendedprice"))}
    return relational.release(relational.group_aggregate(lines, ["l_returnflag", "l_linestatus"], aggs, widths=NARROW, **S))
