"""Relational operators on arrays of public length: filters mark, joins are send-receive, groups are sort and scan.

Results that hide their cardinality carry ``is_real``; ``release`` drops the fillers and makes the true length public.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codec import Key, as_keys
from ..plans.shared import materialise, numbered
from .primitives import prefix_sum, segmented_aggregate, segmented_aggregates, send_receive
from .sorts import oblivious_sort


def where(df: DataFrame, condition: Column) -> DataFrame:
    """All rows stay; those that fail the condition become fillers."""
    now = F.col("is_real") if "is_real" in df.columns else F.lit(True)
    return df.withColumn("is_real", now & F.coalesce(condition, F.lit(False)))


def release(df: DataFrame) -> DataFrame:
    """Drop fillers: the number of real rows becomes public."""
    return df.filter("is_real").drop("is_real") if "is_real" in df.columns else df


def lookup_join(facts: DataFrame, dim: DataFrame, key: str, dim_key: str, values: list[str], how: str = "inner", **options) -> DataFrame:
    """Each fact with the one dimension row of its key. ``inner``: facts without one become fillers; ``left``: nulls; ``semi``, ``anti``: facts alone, marked.

    ``right``: the facts that match, and the dimension rows that no fact asks for, with nulls; ``outer``: those and the facts without a match.
    """
    if how in ("right", "outer"):
        return _with_unasked(facts, dim, key, dim_key, values, how, **options)
    own = {"seed": None, "level": "memory", **options}
    senders = dim.select(F.col(dim_key).cast(facts.schema[key].dataType).alias(key), *values)
    if how in ("semi", "anti"):  # repeated keys stay: the first of each is propagated
        senders, values = senders.select(key).withColumn("_one", F.lit(1)), ["_one"]
    got = send_receive(senders, facts, [key], values, restore=False, **({"on_duplicate": "first"} | own))
    if how == "left":
        return got.drop("found")
    got = where(got, F.col("found") if how != "anti" else ~F.col("found")).drop("found")
    return got.drop("_one") if how in ("semi", "anti") else got


def _with_unasked(facts: DataFrame, dim: DataFrame, key: str, dim_key: str, values: list[str], how: str, **options) -> DataFrame:
    kind, extra = facts.schema[key].dataType, [c for c in facts.columns if c not in (key, "is_real")]
    got = lookup_join(facts, dim, key, dim_key, values, "inner" if how == "right" else "left", **options)
    got = got if "is_real" in got.columns else got.withColumn("is_real", F.lit(True))
    lone = lookup_join(dim.select(F.col(dim_key).cast(kind).alias(key), *values), facts, key, key, [], "anti", **options)
    none = [F.lit(None).cast(facts.schema[c].dataType).alias(c) for c in extra]
    return got.select(key, *extra, *values, "is_real").unionByName(lone.select(key, *none, *values, "is_real"))


def group_aggregate(df: DataFrame, keys: list[str], aggs: dict[str, tuple[str, Column]], **options) -> DataFrame:
    """One real row a group, the leftmost of it, and fillers for the rest. ``aggs``: name -> (f, column); f as in ``segmented_aggregate``, or
    ``avg``, ``var`` and ``std`` (of the sample), ``count_distinct``, or ``min_by`` and ``max_by`` (of (value, order) structs).

    Fillers of the input take no part: they come last in the sort and their values are null.
    """
    for name, (f, c) in aggs.items():
        if f == "count_distinct":  # first the different values of each group, then their number
            others = {k: v for k, v in aggs.items() if k != name}
            flat = df.withColumn("_cd", c)
            once = group_aggregate(flat.select(*[x for x in ("is_real",) if x in df.columns], *keys, "_cd"), [*keys, "_cd"], {}, **options)
            here = group_aggregate(materialise(once, "distinct"), keys, {name: ("count", F.col("_cd"))}, **options)
            if not others:
                return here
            rest = group_aggregate(df, keys, others, **options)
            both = here.withColumns({k: F.lit(None).cast(rest.schema[k].dataType) for k in others}).unionByName(rest.withColumn(name, F.lit(None).cast("long")))
            return group_aggregate(materialise(both, "distinct"), keys, {k: ("max", F.col(k)) for k in aggs}, **options)
    real = F.col("is_real") if "is_real" in df.columns else F.lit(True)
    work, pairs = {}, {}
    for name, (f, c) in aggs.items():
        if f in ("avg", "var", "std"):
            work[f"_s_{name}"], work[f"_n_{name}"] = ("sum", c.cast("double") if f != "avg" else c), ("count", c)
            if f != "avg":
                work[f"_q_{name}"] = ("sum", (c * c).cast("double"))
        elif f in ("min_by", "max_by"):
            work[name], pairs = (f[:3], c.getField("value")), {**pairs, name: c.getField("by")}
        else:
            work[name] = (f, c)
    rows = df.select(real.alias("_real"), *keys, *(F.when(real, c).alias(f"_v_{n}") for n, (_, c) in work.items()), *(F.when(real, c).alias(f"_b_{n}") for n, c in pairs.items()))
    n = rows.count()
    rows = materialise(oblivious_sort(rows, [Key("_real", False), *as_keys(keys)], pos="_p", **options), "grouped")
    group = ["_real", *keys]
    # one scan for all: every function is taken over the suffix, so the leftmost row has its group's total
    if work:
        rows = segmented_aggregates(rows, group, {name: (f, F.col(f"_v_{name}") if name not in pairs else F.when(F.col(f"_b_{name}").isNotNull(), F.struct(f"_b_{name}", F.col(f"_v_{name}").alias("value")))) for name, (f, _) in work.items()}, True, "suffix", "_p", n=n)
    line = Window.partitionBy("_blk0").orderBy("_p")
    size = max(1, -(-n // int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    rows = rows.withColumn("_blk0", F.floor(F.col("_p") / size).cast("int")).withColumn("_g", F.struct(*group))
    ends = rows.groupBy("_blk0").agg(F.max_by("_g", "_p").alias("_end")).select((F.col("_blk0") + 1).alias("_blk0"), "_end")
    rows = rows.join(F.broadcast(ends), "_blk0", "left")
    before = F.coalesce(F.lag("_g").over(line), F.col("_end"))
    first = ~before.eqNullSafe(F.col("_g")) | (F.col("_p") == 0)
    out = {}
    for name, (f, _) in aggs.items():
        s, m, q = (F.col(f"_{x}_{name}") for x in "snq")
        if f in ("var", "std"):
            spread = F.when(m > 1, F.greatest((q - s * s / m) / (m - 1), F.lit(0.0)))
            out[name] = F.sqrt(spread) if f == "std" else spread
        else:
            out[name] = F.try_divide(s, m) if f == "avg" else F.col(name)["value"] if f in ("min_by", "max_by") else F.col(name)
    return rows.select(*keys, *(c.alias(k) for k, c in out.items()), (first & F.col("_real")).alias("is_real"))


def distinct(df: DataFrame, **options) -> DataFrame:
    """One real row for each combination of values."""
    cols = [c for c in df.columns if c != "is_real"]
    return group_aggregate(df, cols, {}, **options)


def top_k(df: DataFrame, k: int, keys, **options) -> DataFrame:
    """The first ``k`` (public) rows of the order, with ``pos``."""
    if "is_real" in df.columns:
        done = oblivious_sort(df, [Key("is_real", False), *as_keys(keys)], pos="pos", **options)
    else:
        done = oblivious_sort(df, keys, pos="pos", **options)
    return done.filter(F.col("pos") < k)


def grouping_sets(df: DataFrame, sets: list[list[str]], aggs: dict[str, tuple[str, Column]], **options) -> DataFrame:
    """Rows repeated once a set, columns outside it null, ``grouping_id`` the set's number."""
    cols = sorted({c for s in sets for c in s})
    copies = F.array(*[F.struct(F.lit(i).alias("grouping_id"), *[(F.col(c) if c in s else F.lit(None).cast(df.schema[c].dataType)).alias(f"_k_{c}") for c in cols]) for i, s in enumerate(sets)])
    rows = df.withColumn("_set", F.explode(copies)).select(*[c for c in df.columns if c not in cols], "_set.*", *[F.col(c).alias(f"_o_{c}") for c in cols])
    rows = rows.withColumnsRenamed({f"_k_{c}": c for c in cols})
    return group_aggregate(rows, ["grouping_id", *cols], aggs, **options)


def rollup(keys: list[str]) -> list[list[str]]:
    return [keys[:i] for i in range(len(keys), -1, -1)]


def cube(keys: list[str]) -> list[list[str]]:
    return [[k for i, k in enumerate(keys) if m >> i & 1] for m in range((1 << len(keys)) - 1, -1, -1)]


def set_operation(a: DataFrame, b: DataFrame, kind: str, **options) -> DataFrame:
    """``union``, ``intersect`` or ``except``, each distinct; length of both together, losers are fillers."""
    both = a.withColumn("_s", F.lit(0)).unionByName(b.withColumn("_s", F.lit(1)))
    got = group_aggregate(both, a.columns, {"_lo": ("min", F.col("_s")), "_hi": ("max", F.col("_s"))}, **options)
    keep = {"union": F.lit(True), "intersect": (F.col("_lo") == 0) & (F.col("_hi") == 1), "except": F.col("_hi") == 0}[kind]
    return where(got, keep).drop("_lo", "_hi")


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, values: list[str], **options) -> DataFrame:
    """Each left row with the values of the latest right row of its key at or before ``at``; one sort of both, one prefix scan."""
    kinds = {f.name: f.dataType for f in [*left.schema.fields, *right.schema.fields]}
    extra = [c for c in left.columns if c not in (key, at)]
    none = lambda c: F.lit(None).cast(kinds[c]).alias(c)
    both = right.select(key, at, *values, *(none(c) for c in extra), F.lit(0).alias("_r")).unionByName(left.select(key, at, *(none(c) for c in values), *extra, F.lit(1).alias("_r")))
    rows = materialise(oblivious_sort(both, [Key(key), Key(at), Key("_r")], pos="_p", **options), "as-of")
    # the latest sender so far: positions rise, so it is the one of the largest position
    last = segmented_aggregate(rows, [key], F.when(F.col("_r") == 0, F.struct(F.col("_p").alias("p"), *values)), "max", "_last", True, "prefix", "_p")
    return last.filter("_r = 1").select(key, at, *extra, *(F.col("_last")[v].alias(v) for v in values))


def window_ranks(df: DataFrame, partition: list[str], order, **options) -> DataFrame:
    """``row_number``, ``rank``, ``dense_rank`` of each row: a sort and prefix scans."""
    keys = [*as_keys(partition), *as_keys(order)]
    rows = materialise(oblivious_sort(df, keys, pos="_p", **options), "ranked")
    rows = segmented_aggregate(rows, partition, F.lit(1), "count", "row_number", True, "prefix", "_p")
    named = [k.name for k in as_keys(order)]
    rows = segmented_aggregate(rows, [*partition, *named], F.col("_p"), "min", "_tie", True, "prefix", "_p")
    rows = rows.withColumn("_new", (F.col("_tie") == F.col("_p")).cast("long"))
    rows = segmented_aggregate(materialise(rows, "ranked"), partition, F.col("_new"), "sum", "dense_rank", True, "prefix", "_p")
    return rows.withColumn("rank", F.col("row_number") - (F.col("_p") - F.col("_tie"))).drop("_p", "_tie", "_new")


def expand_join(left: DataFrame, right: DataFrame, key: str, bound: int, **options) -> DataFrame:
    """Equi join of many with many, up to ``bound`` (public) result rows: counts by scans, then each left row is copied once a match.

    Right rows are numbered within their key; a left row asks for the numbers 0 .. matches - 1, and each copy is a lookup by (key, number). Left rows are
    put at the running sum of their matches in an array of ``bound`` places, and every place learns the latest row before it: copies are made without a row growing by a
    secret number. The result has ``bound`` rows, ``is_real`` on those that are; ``release`` makes their number public.
    """
    n = materialise(oblivious_sort(right, [key], pos="_p", **options), "expand")
    n = materialise(segmented_aggregate(n, [key], F.lit(1), "count", "_i", False, "prefix", "_p").drop("_p"), "expand")
    sizes = release(group_aggregate(n, [key], {"_n": ("count", F.lit(1))}, **options))
    asked = lookup_join(left, sizes, key, key, ["_n"], how="left", **options).withColumn("_n", F.coalesce("_n", F.lit(0)))
    asked = materialise(numbered(asked, "_at"), "expand")
    asked = materialise(prefix_sum(asked, F.col("_n"), "_from", False, "_at"), "expand")
    total = asked.agg(F.coalesce(F.max(F.col("_from") + F.col("_n")), F.lit(0))).first()[0]
    if total > bound:
        raise ValueError(f"the join has {total} rows, its bound is {bound}")
    spark, own = left.sparkSession, left.columns
    places = spark.range(bound).select(F.col("id").alias("_from"), F.lit(1).alias("_kind"))
    both = asked.select(*own, F.when(F.col("_n") > 0, F.col("_from")).alias("_from"), F.lit(0).alias("_kind")).unionByName(places, allowMissingColumns=True)
    both = materialise(oblivious_sort(both, [Key("_from", True, False), Key("_kind")], pos="_p", **options), "expand")
    latest = segmented_aggregate(both, [], F.when((F.col("_kind") == 0) & F.col("_from").isNotNull(), F.struct(F.col("_p").alias("p"), F.col("_from").alias("f"), *[F.col(c) for c in own])), "max", "_last", True, "prefix", "_p")
    copies = latest.filter("_kind = 1").select(*[F.when(F.col("_from") < total, F.col("_last")[c]).alias(c) for c in own], (F.col("_from") - F.col("_last.f")).alias("_i"), (F.col("_from") < total).alias("is_real"))
    values = [c for c in right.columns if c != key]
    got = send_receive(n.select(key, "_i", *values), materialise(copies, "expand"), [key, "_i"], values, restore=False, on_duplicate="first", **options)
    return got.drop("found", "_i")


def public_join(facts: DataFrame, dim: DataFrame, key: str, dim_key: str, values: list[str], most: int = 4096) -> DataFrame:
    """A small public dimension, looked up by a scan of all its entries in every row."""
    rows = dim.select(dim_key, *values).limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"a public dimension has at most {most} rows")
    for v in values:
        kind = dim.schema[v].dataType
        pick = reduce(lambda acc, r: F.when(F.col(key) == F.lit(r[dim_key]), F.lit(r[v]).cast(kind)).otherwise(acc), rows, F.lit(None).cast(kind))
        facts = facts.withColumn(v, pick)
    return facts


def having(groups: DataFrame, condition: Column) -> DataFrame:
    """Groups that fail become fillers."""
    return where(groups, condition)


def pivot(df: DataFrame, keys: list[str], by: str, values: list, aggs: dict[str, tuple[str, Column]], **options) -> DataFrame:
    """A column for each public value of ``by`` and each aggregate, named value_aggregate; the values come from the caller, not from the data."""
    wide = {f"{v}_{name}": (f, F.when(F.col(by) == F.lit(v), c)) for v in values for name, (f, c) in aggs.items()}
    return group_aggregate(df, keys, wide, **options)


def sample(df: DataFrame, share: float, seed: int | None = None) -> DataFrame:
    """All rows stay; each is real with probability ``share``, by a keyed hash of its place."""
    from ..functions.kernels import coin_key

    key = coin_key(seed)
    a, b = (int.from_bytes(key[i : i + 8], "little", signed=True) for i in (0, 8))
    rows = numbered(df, "_at")
    draw = F.pmod(F.xxhash64(F.lit(a), F.col("_at"), F.lit(b)), F.lit(1 << 40))
    return where(rows, draw < int(share * (1 << 40))).drop("_at")


def quantiles(df: DataFrame, value: str, shares: list[float], **options) -> DataFrame:
    """(share, value): the element at place floor(share * (n - 1)) of the n rows, by an oblivious sort; places are public."""
    done = materialise(oblivious_sort(df.select(value), [value], pos="_p", **options), "quantiles")
    n = done.count()
    at = df.sparkSession.createDataFrame([(float(s), int(s * (n - 1))) for s in shares] if n else [], "share double, _at long")
    return done.join(F.broadcast(at), F.col("_p") == F.col("_at")).select("share", value)


def neighbour(df: DataFrame, partition: list[str], order, value: Column, out: str, steps: int = 1, **options) -> DataFrame:
    """``value`` of the row ``steps`` before (lag) or, negative, after (lead) in its partition's order, else null: places shift by a public number."""
    rows = materialise(oblivious_sort(df, [*as_keys(partition), *as_keys(order)], pos="_p", **options), "neighbours")
    group = F.struct(*[F.col(c) for c in partition]) if partition else F.struct(F.lit(0))
    other = rows.select((F.col("_p") + steps).alias("_q"), group.alias("_g"), value.alias("_v"))
    got = rows.withColumn("_own", group).join(other, F.col("_p") == F.col("_q"), "left")
    return got.withColumn(out, F.when(F.col("_own").eqNullSafe(F.col("_g")), F.col("_v"))).drop("_p", "_q", "_g", "_v", "_own")


def first_last(df: DataFrame, partition: list[str], order, value: Column, first: str = "first_value", last: str = "last_value", **options) -> DataFrame:
    """The value at the start and at the end of each row's partition."""
    rows = materialise(oblivious_sort(df, [*as_keys(partition), *as_keys(order)], pos="_p", **options), "ends")
    rows = segmented_aggregate(rows, partition, F.struct(value.alias("x")), "first", "_f", True, "prefix", "_p")
    rows = segmented_aggregate(materialise(rows, "ends"), partition, F.struct(value.alias("x")), "first", "_l", True, "suffix", "_p")
    return rows.withColumn(first, F.col("_f.x")).withColumn(last, F.col("_l.x")).drop("_f", "_l", "_p")


def frame_sum(df: DataFrame, partition: list[str], order, value: Column, out: str, before: int, after: int = 0, **options) -> DataFrame:
    """Sum over the rows from ``before`` before to ``after`` after in the partition: a difference of two running sums, read at public distances."""
    rows = materialise(oblivious_sort(df, [*as_keys(partition), *as_keys(order)], pos="_p", **options), "frames")
    rows = segmented_aggregates(rows, partition, {"_run": ("sum", value), "_i": ("count", F.lit(1))}, True, "prefix", "_p")
    rows = materialise(segmented_aggregates(rows, partition, {"_left": ("count", F.lit(1)), "_more": ("sum", value)}, False, "suffix", "_p"), "frames")
    run = rows.select(F.col("_p").alias("_q"), F.col("_run").alias("_r"))
    far = rows.withColumn("_to", F.col("_p") + F.least(F.lit(after), F.col("_left"))).withColumn("_from", F.when(F.col("_i") > before + 1, F.col("_p") - before - 1))
    ahead = run.select((F.col("_q") - after).alias("_a"), F.col("_r").alias("_hi"))
    behind = run.select((F.col("_q") + before + 1).alias("_b"), F.col("_r").alias("_lo"))
    got = far.join(ahead, F.col("_p") == F.col("_a"), "left").join(behind, F.col("_p") == F.col("_b"), "left")
    top = F.when(F.col("_left") >= after, F.col("_hi")).otherwise(F.col("_run") + F.coalesce("_more", F.lit(0)))
    return got.withColumn(out, top - F.when(F.col("_i") > before + 1, F.col("_lo")).otherwise(0)).drop("_p", "_run", "_i", "_left", "_more", "_to", "_from", "_a", "_hi", "_b", "_lo")


def window_shares(df: DataFrame, partition: list[str], order, tiles: int, **options) -> DataFrame:
    """``ntile`` of each row among ``tiles``, ``percent_rank`` and ``cume_dist``: ranks over counts of the partition."""
    rows = materialise(window_ranks(df, partition, order, **options), "shares")
    named = [k.name for k in as_keys(order)]
    rows = materialise(oblivious_sort(rows, [*as_keys(partition), Key("row_number")], pos="_p", **options), "shares")
    rows = segmented_aggregates(rows, partition, {"_before": ("count", F.lit(1))}, True, "prefix", "_p")
    rows = segmented_aggregates(materialise(rows, "shares"), partition, {"_after": ("count", F.lit(1))}, False, "suffix", "_p")
    rows = segmented_aggregates(materialise(rows, "shares"), [*partition, *named], {"_ties": ("count", F.lit(1))}, False, "suffix", "_p")
    n = F.col("_before") + F.col("_after")
    small, extra = F.floor(n / tiles), n % tiles
    i = F.col("row_number") - 1
    tile = F.when(i < extra * (small + 1), F.floor(i / (small + 1))).otherwise(extra + F.floor((i - extra * (small + 1)) / F.greatest(small, F.lit(1)))) + 1
    return rows.withColumns({
        "ntile": tile.cast("int"), "percent_rank": F.when(n > 1, (F.col("rank") - 1) / (n - 1)).otherwise(0.0), "cume_dist": (F.col("row_number") + F.col("_ties")) / n,
    }).drop("_p", "_before", "_after", "_ties")


def range_join(left: DataFrame, right: DataFrame, at: str, low: str, high: str, values: list[str], **options) -> DataFrame:
    """Each left row with the values of the right range [low, high) that its ``at`` lies in; ranges don't overlap. One sort of both, one scan."""
    both = left.select(at, *[c for c in left.columns if c != at]).withColumn("_k", F.lit(0))
    got = as_of_join(both, right.select(F.lit(0).alias("_k"), F.col(low).alias(at), F.col(high).alias("_high"), *values), "_k", at, ["_high", *values], **options)
    inside = F.col("_high").isNotNull() & (F.col(at) < F.col("_high"))
    return got.select(*left.columns, *(F.when(inside, F.col(v)).alias(v) for v in values))


def theta_join(left: DataFrame, right: DataFrame, condition: Column, most: int = 4096) -> DataFrame:
    """Every pair of a left row and one of at most ``most`` (public) right rows, marked as real where ``condition`` holds: the whole product, as hiding the matches demands."""
    if right.limit(most + 1).count() > most:
        raise ValueError(f"the side that every row is paired with has at most {most} rows")
    rows = right.select(F.struct(*right.columns).alias("_r")).agg(F.collect_list("_r").alias("_all"))
    wide = left.join(F.broadcast(rows)).select(*left.columns, F.explode("_all").alias("_r")).select(*left.columns, "_r.*")
    return where(wide, condition)
