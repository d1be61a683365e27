"""Benchmark decontamination by an Aho-Corasick automaton over the benchmark's word windows."""

from __future__ import annotations

import hashlib
import pickle
import uuid
from itertools import repeat

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.shared import materialise
from .base import column, id_and_text, map_batches, texts_of, unused

#: Fixed value: bytes that words are made of (after lower-casing); all others part words.
_WORD_BYTES = b"0123456789abcdefghijklmnopqrstuvwxyz" + bytes(range(128, 256))
#: From any byte to its lower-case word byte, or a space.
NORMAL = bytes(c if c in _WORD_BYTES else 32 for c in bytes(range(256)).lower())
#: Windows that one automaton holds; a benchmark of more is scanned for in rounds, each with an automaton of its own. There are codes for two million different words.
ROUND_WINDOWS = 1 << 16


def normal_words(text: bytes) -> list[bytes]:
    """Words of a UTF-8 text: runs of ASCII digits, letters (lower-cased) and wider characters."""
    return text.translate(NORMAL).split()


def windows(words: list[bytes], width: int) -> list[bytes]:
    if not words:
        return []
    return [b" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))]


def _code(number: int) -> str:
    """Three characters for a word number, the first of an alphabet that the others don't have: a match can't begin inside a word. Few characters keep the automaton's nodes narrow."""
    return chr(number >> 14) + chr(128 + (number >> 7 & 127)) + chr(128 + (number & 127))


_UNKNOWN = _code(0)


class Scanner:
    """One Aho-Corasick automaton over windows, written as three characters a word; words that no window has are number 0."""

    def __init__(self, owners: list[tuple[bytes, list]]):
        self.codes: dict[bytes, str] = {}
        self.machine = ahocorasick.Automaton()
        for window, of in owners:
            words = window.split(b" ")
            for w in words:
                if w not in self.codes:
                    self.codes[w] = _code(len(self.codes) + 1)
            self.machine.add_word("".join([self.codes[w] for w in words]), (len(words), tuple(of)))
        if owners:
            self.machine.make_automaton()

    def hits(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set]:
        """Word ranges (first, past the last) that windows cover, merged, and the items they are of."""
        found, items = [], set()
        if not words or not len(self.machine):
            return found, items
        for at, (n, of) in self.machine.iter("".join(map(self.codes.get, words, repeat(_UNKNOWN)))):
            past = (at + 1) // 3
            found.append((past - n, past))
            items.update(of)
        return merged(found), items


def merged(found: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Overlapping and touching ranges as one."""
    spans: list[tuple[int, int]] = []
    for a, b in sorted(found):
        if spans and a <= spans[-1][1]:
            spans[-1] = (spans[-1][0], max(b, spans[-1][1]))
        else:
            spans.append((a, b))
    return spans


_loaded: dict[str, Scanner] = {}


def benchmark_windows(items: DataFrame, width: int) -> DataFrame:
    """(window, item): each different window of an item, in tasks; a null item is kept as such."""

    def kernel(batches):
        for batch in batches:
            for item, text in zip(column(batch, "item").to_pylist(), texts_of(batch)):
                own = list(set(windows(normal_words(text), width)))
                for at in range(0, len(own), 4096):
                    part = own[at : at + 4096]
                    yield pa.record_batch([pa.array(part, pa.binary()), pa.array([item] * len(part), pa.string())], names=["window", "item"])

    return map_batches(items, kernel, "window binary, item string")


def _rounds(table: DataFrame, most: int):
    """Of each round a broadcast scanner, built from at most about ``most`` windows, and a key for the workers."""
    count = table.select("window").distinct().count()
    rounds = max(1, -(-count // most))
    for i in range(rounds):
        mine = table.filter(F.pmod(F.xxhash64("window"), F.lit(rounds)) == i).groupBy("window").agg(F.collect_set(F.struct("item")).alias("of"))
        owners = [(bytes(r["window"]), [x["item"] for x in r["of"]]) for r in mine.toLocalIterator()]
        yield table.sparkSession.sparkContext.broadcast(pickle.dumps(Scanner(owners))), uuid.uuid4().hex, rounds


def _scanner(shared, name: str) -> Scanner:
    if name not in _loaded:
        _loaded.clear()
        _loaded[name] = pickle.loads(shared.value)
    return _loaded[name]


def word_offsets(text: bytes) -> np.ndarray:
    """(start, end) in bytes of each word in the original text."""
    inside = np.frombuffer(text.translate(NORMAL), np.uint8) != 32
    edge = np.flatnonzero(np.diff(np.concatenate(([False], inside, [False])).astype(np.int8)))
    return edge.reshape(-1, 2)


_SPANS = "array<struct<a:int,b:int>>"


def _found_in_rounds(base: DataFrame, rounds: list) -> DataFrame:
    """(row, found, items): what each round's scanner finds, in one job a round and brought together by row."""
    parts = []
    for shared, name, _ in rounds:

        def scan(batches, shared=shared, name=name):
            scanner = _scanner(shared, name)
            for batch in batches:
                got = [(i, *scanner.hits(normal_words(t))) for i, t in zip(column(batch, "row").to_pylist(), texts_of(batch))]
                got = [g for g in got if g[1]]
                yield pa.record_batch(
                    [pa.array([g[0] for g in got], pa.int64()), pa.array([[{"a": a, "b": b} for a, b in g[1]] for g in got], pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32())]))), pa.array([list(g[2]) for g in got], pa.list_(pa.string()))],
                    names=["row", "found", "items"],
                )

        parts.append(materialise(map_batches(base.select("row", "text"), scan, f"row long, found {_SPANS}, items array<string>"), "hits"))
        shared.unpersist()
    whole = parts[0]
    for part in parts[1:]:
        whole = whole.unionByName(part)
    return whole.groupBy("row").agg(F.flatten(F.collect_list("found")).alias("found"), F.flatten(F.collect_list("items")).alias("items"))


def decontaminate(
    docs: DataFrame, benchmark: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text",
    item_col: str = "item_id", item_text_col: str = "text", carry: bool = False, round_windows: int = ROUND_WINDOWS,
) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated, spans (with ``carry``: all input columns instead of doc_id, and last contaminated under a name that is free).

    A window is ``width`` consecutive words of a benchmark item, or the whole of a shorter item. The different windows are
    found in tasks and written down; about ``round_windows`` of them at a time go into one automaton over words, which reads each document's words
    once. A word inside any match is hit. ``spans`` gives the hit parts as byte ranges of the original text (UTF-8), punctuation
    between hit words included. A benchmark of any size is served: with more windows than one automaton takes, the documents are read once a round,
    what the rounds find is brought together by row, and the result is the same.

    Null or empty text, or one without words: no words, no hit. Items without words and null items' texts have no window;
    a null item_id counts as an item but has no name in the hash. Several items with one text all count. Empty tables: no
    rows, or no hits. Null or repeated doc_ids: one row for each input row. Other columns are ignored or carried.
    """
    table = materialise(benchmark_windows(id_and_text(benchmark, item_col, item_text_col).select(F.col("doc_id").cast("string").alias("item"), "text"), width), "windows")
    rounds = _rounds(table, round_windows)
    shared, name, several = next(rounds)
    base = id_and_text(docs, id_col, text_col, *([F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")] if carry else []))
    own = "_row" if carry else "doc_id"
    if several > 1:
        base = materialise(base.withColumn("row", F.monotonically_increasing_id()), "numbered")
        base = base.join(_found_in_rounds(base, [(shared, name, several), *rounds]).withColumnRenamed("row", "_r"), F.col("row") == F.col("_r"), "left")
        base = base.select(own, "text", "found", "items")
    else:
        base = base.select(own, "text")

    def kernel(batches):
        scanner = _scanner(shared, name) if several == 1 else None
        for batch in batches:
            cols = {k: [] for k in ("n_words", "n_hit", "n_items", "items_sha256", "contaminated", "spans")}
            texts = texts_of(batch)
            told = zip(column(batch, "found").to_pylist(), column(batch, "items").to_pylist()) if several > 1 else [(None, None)] * len(texts)
            for text, (spans, found) in zip(texts, told):
                words = normal_words(text)
                spans, found = scanner.hits(words) if several == 1 else (merged([(x["a"], x["b"]) for x in spans or []]), set(found or []))
                where = word_offsets(text) if spans else None
                hit = sum(b - a for a, b in spans)
                names = ",".join(sorted(x for x in found if x is not None))
                cols["n_words"].append(len(words))
                cols["n_hit"].append(hit)
                cols["n_items"].append(len(found))
                cols["items_sha256"].append(hashlib.sha256(names.encode()).hexdigest())
                cols["contaminated"].append(hit > 0)
                cols["spans"].append([{"start": int(where[a, 0]), "end": int(where[b - 1, 1])} for a, b in spans])
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
            yield pa.record_batch([column(batch, own), *(pa.array(v, t) for v, t in zip(cols.values(), kinds))], names=[own, *cols])

    facts = "n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, spans array<struct<start:long,end:long>>"
    out = map_batches(base, kernel, f"{own} {base.schema[own].dataType.simpleString()}, {facts}")
    return out.select(*[F.col("_row")[c].alias(c) for c in docs.columns], F.col("contaminated").alias(unused(docs, "_contaminated"))) if carry else out
