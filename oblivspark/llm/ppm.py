"""Language-model scoring by prediction by partial matching over bytes, beside a word-count base.

The trie is dealt over tasks at every size. Blocks of documents ask for each of their distinct grams once; the distinct grams of the
corpus are dealt by range of their contexts, newest symbol first, so that a task holds whole subtrees of the trie.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.shared import fixed_rows, materialise
from .base import column, id_and_text, map_batches, texts_of
from .quality import remainder

#: Bits per symbol; the symbol before a text's first byte, and, when it is to be predicted, the one after its last.
BITS, EDGE = 9, 256
#: Length of the longest context in bytes.
ORDER = 5
#: Symbols coded at a time, and distinct grams that a block gathers before it merges them.
CHUNK, HELD = 1 << 19, 1 << 20
#: Bytes of text in a block, and bytes from which a text is a block of its own.
BLOCK_BYTES = 16 << 20
#: Least number of slices of the grams (and of the words), and bytes of text per slice where there is more of it.
SLICES, SLICE_BYTES = 64, 1 << 28
#: Distinct grams that a shard of the trie aims at, the most shards, and grams that splitters are picked from.
SHARD_GRAMS, MOST_SHARDS, SPLITTER_SAMPLE = 1 << 18, 1 << 12, 1 << 16
#: Bytes of a text that are cut into words at a time.
WORD_BYTES = 1 << 20
_BLANK = re.compile(rb"[\x20\x09-\x0D]")
_NINE, _SYMBOL, _ODD = np.uint64(BITS), np.uint64((1 << BITS) - 1), np.uint64(0x9E3779B97F4A7C15)


def grams_of(text: bytes, order: int = ORDER, start: int = 0, end: int | None = None) -> np.ndarray:
    """The grams at places ``start`` to ``end`` (all by default) of a text's bytes and its end.

    A gram is ``order`` symbols of context, the newest in the highest bits, then the symbol, packed into 64 bits: grams in order
    of their numbers stand by context, and the contexts that share their newest symbols stand together.
    """
    end = len(text) + 1 if end is None else end
    sym = np.full(end - start + order, EDGE, np.uint64)
    have = max(start - order, 0)
    piece = np.frombuffer(text, np.uint8, min(end, len(text)) - have, have) if len(text) > have else np.empty(0, np.uint8)
    sym[have - start + order : have - start + order + len(piece)] = piece
    n, out = end - start, None
    for back in range(1, order + 1):
        now = sym[order - back : order - back + n]
        out = now.copy() if out is None else (out << _NINE) | now
    return sym[order:] if out is None else (out << _NINE) | sym[order:]


def pieces_of(texts: list[bytes], order: int, chunk: int = CHUNK):
    """(places in the list, grams, length of each): whole short texts together, a long one in pieces, about ``chunk`` grams at a time."""
    at, parts, held = [], [], 0
    for i, text in enumerate(texts):
        for start in range(0, len(text) + 1, chunk):
            part = grams_of(text, order, start, min(start + chunk, len(text) + 1))
            if held + len(part) > chunk and parts:
                yield at, np.concatenate(parts), [len(p) for p in parts]
                at, parts, held = [], [], 0
            at.append(i)
            parts.append(part)
            held += len(part)
    if parts:
        yield at, np.concatenate(parts), [len(p) for p in parts]


def words_of(text: bytes):
    """Lists of a text's words (A to Z lower-cased), about ``WORD_BYTES`` of text at a time."""
    at = 0
    while at < len(text):
        blank = _BLANK.search(text, at + WORD_BYTES) if len(text) - at > WORD_BYTES else None
        end = blank.start() if blank else len(text)
        yield text[at:end].lower().split()
        at = end + 1


def find(keys: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Place of each wanted key among sorted distinct keys, -1 where it is unknown."""
    if not len(keys):
        return np.full(len(wanted), -1, np.int64)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return np.where(keys[at] == wanted, at, -1)


def context_at(grams: np.ndarray, k: int, order: int) -> np.ndarray:
    """The newest ``k`` symbols of each gram's context."""
    return grams >> np.uint64(BITS * (order + 1 - k))


def spanning(splitters: np.ndarray, order: int) -> list[np.ndarray]:
    """For each length below ``order`` the contexts whose grams lie on both sides of a splitter."""
    out = []
    for k in range(order):
        shift = np.uint64(BITS * (order - k))
        out.append(np.unique(splitters[(splitters >> shift << shift) != splitters] >> shift))
    return out


class Trie:
    """Counts of every context of 0 to ``order`` symbols, with escape estimation and symbol exclusion.

    At a context with total T and D distinct symbols, of which the next longer context has X and E, a symbol
    that the longer one lacks gets (2 count - 1) / 2(T - X) and the escape (D - E) / 2(T - X); a context
    with nothing new escapes for free. Under the empty context all symbols not seen share what is left.
    Of a trie that is dealt, ``shared`` has for each length the whole counts of contexts that several parts have: (contexts, keys, counts).
    """

    def __init__(self, grams: np.ndarray, counts: np.ndarray, order: int = ORDER, shared: list[tuple] | None = None):
        self.order, self.levels = order, []
        grams, counts = grams[counts > 0], counts[counts > 0].astype(np.int64)
        for k in range(order, -1, -1):
            keys, n = _merge([context_at(grams, k, order) << _NINE | grams & _SYMBOL], [counts])
            if shared and k < order:
                across, more, times = shared[k]
                own = find(across, keys >> _NINE) < 0
                keys, n = _merge([keys[own], more], [n[own], times])
            contexts, first = np.unique(keys >> _NINE, return_index=True)
            total = np.add.reduceat(n, first) if len(first) else n[:0]
            self.levels.append({"keys": keys, "n": n, "contexts": contexts, "total": total, "kinds": np.diff(np.append(first, len(keys))), "first": first})
        # what a longer context takes out of the next shorter one
        for upper, lower in zip(self.levels, self.levels[1:]):
            keys = upper["keys"]
            inside = lower["n"][find(lower["keys"], keys >> (_NINE + _NINE) << _NINE | keys & _SYMBOL)]
            upper["taken"] = np.add.reduceat(inside, upper["first"]) if len(keys) else inside[:0]

    def log10(self, grams: np.ndarray) -> np.ndarray:
        """Log10 probability of each gram's last symbol after its context."""
        out = np.zeros(len(grams))
        open_ = np.arange(len(grams))
        taken, gone = np.zeros(len(grams), np.int64), np.zeros(len(grams), np.int64)
        for depth, level in enumerate(self.levels):
            if not len(open_):
                return out
            context = context_at(grams[open_], self.order - depth, self.order)
            c = find(level["contexts"], context)
            seen = c >= 0
            at, c, key = open_[seen], c[seen], context[seen] << _NINE | grams[open_[seen]] & _SYMBOL
            total, kinds = level["total"][c] - taken[at], level["kinds"][c] - gone[at]
            k = find(level["keys"], key)
            hit = k >= 0
            out[at[hit]] += np.log10((2 * level["n"][k[hit]] - 1) / (2 * total[hit]))
            miss = ~hit
            esc = miss & (kinds > 0)
            out[at[esc]] += np.log10(kinds[esc] / (2 * total[esc]))
            gone[at[miss]] = level["kinds"][c[miss]]
            if "taken" in level:
                taken[at[miss]] = level["taken"][c[miss]]
            done = np.zeros(len(grams), bool)
            done[at[hit]] = True
            open_ = open_[~done[open_]]
        out[open_] -= np.log10(np.maximum(EDGE + 1 - gone[open_], 1))
        return out


def adaptive_log10(text: bytes, order: int = ORDER) -> float:
    """Log10 probability of a text by a model that learns from the text itself, symbol by symbol (escape method and exclusion as in ``Trie``)."""
    seen: dict[tuple, dict[int, int]] = {}
    history, total = (EDGE,) * order, 0.0
    for s in [*text, EDGE]:
        excluded: set[int] = set()
        for k in range(order, -1, -1):
            known = seen.get(history[order - k :], {})
            left = {c: n for c, n in known.items() if c not in excluded}
            whole = 2 * sum(left.values())
            if s in left:
                total += math.log10((2 * left[s] - 1) / whole)
                break
            if left:
                total += math.log10(len(left) / whole)
            excluded |= known.keys()
        else:
            total -= math.log10(max(EDGE + 1 - len(excluded), 1))
        for k in range(order + 1):
            own = seen.setdefault(history[order - k :], {})
            own[s] = own.get(s, 0) + 1
        history = (*history[1:], s) if order else ()
    return total


def _merge(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in order and the sums of their counts."""
    k, n = np.concatenate(keys), np.concatenate(counts)
    if len(k) > 1 and (k[1:] < k[:-1]).any():
        by = np.argsort(k)
        k, n = k[by], n[by]
    first = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1]))) if len(k) else np.empty(0, np.int64)
    n = np.add.reduceat(n.astype(np.int64), first) if len(k) else n.astype(np.int64)
    return k[first], n


def slices_of(keys: np.ndarray, slices: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return ((keys * _ODD >> np.uint64(32)) % np.uint64(slices)).astype(np.int64)


def by_slice(keys: np.ndarray, slices: int) -> list[tuple[int, np.ndarray]]:
    """(slice, places of its keys, in order) for each slice that has some."""
    slot = slices_of(keys, slices)
    by = np.argsort(slot, kind="stable")
    cut = np.searchsorted(slot[by], np.arange(slices + 1))
    return [(i, by[a:b]) for i, (a, b) in enumerate(zip(cut, cut[1:])) if b > a]


def word_hashes(words: list[bytes]) -> np.ndarray:
    h = xxhash.xxh3_64_intdigest
    return np.array([h(w) for w in words], np.uint64)


def counted_grams(texts: list[bytes], train: list[bool], order: int) -> tuple[np.ndarray, np.ndarray]:
    """A block's distinct grams in order, and how often each is in its training texts."""
    keys, counts, size = [np.empty(0, np.uint64)], [np.empty(0, np.int64)], 0
    for learn in (True, False):
        for _, flat, _ in pieces_of([t for t, mine in zip(texts, train) if mine == learn], order):
            k, n = np.unique(flat, return_counts=True)
            keys.append(k)
            counts.append(n if learn else np.zeros(len(k), np.int64))
            size += len(k)
            if size >= HELD:
                k, n = _merge(keys, counts)
                keys, counts, size = [k], [n], 0
    return _merge(keys, counts)


def counted_words(texts: list[bytes], train: list[bool]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of a block's distinct words in order, and how often each is in its training texts; the empty word stands for a text's end."""
    learnt, other = Counter(), Counter()
    for text, learn in zip(texts, train):
        for words in words_of(text):
            (learnt if learn else other).update(words)
        (learnt if learn else other)[b""] += 1
    new = [w for w in other if w not in learnt]
    return _merge([word_hashes([*learnt, *new])], [np.array([*learnt.values(), *[0] * len(new)], np.int64)])


def packed(a: np.ndarray) -> bytes:
    """Numbers byte by byte of the same weight: what changes slowly is left to the exchange's compression."""
    return np.ascontiguousarray(a.view(np.uint8).reshape(len(a), a.itemsize).T).tobytes()


def unpacked(b: bytes, kind: str = "<u8") -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(size, -1).T).view(kind).ravel()


def _unpacked(parts) -> list[np.ndarray]:
    return [np.empty(0, np.uint64), *(unpacked(b) for b in parts.to_pylist())]


def blocks_of(batches, block_bytes: int):
    """(number, ids, held out, texts) of a task's blocks: the same whenever the task runs over the same rows."""
    task, done, ids, held, texts, size = TaskContext.get().partitionId(), 0, [], [], [], 0
    for batch in batches:
        for i, h, text in zip(column(batch, "doc_id").to_pylist(), column(batch, "held_out").to_pylist(), texts_of(batch)):
            if texts and size + len(text) > block_bytes:
                yield (task << 32) | done, ids, held, texts
                done, ids, held, texts, size = done + 1, [], [], [], 0
            ids.append(i)
            held.append(h)
            texts.append(text)
            size += len(text)
    if texts:
        yield (task << 32) | done, ids, held, texts


def asked_by_blocks(base: DataFrame, order: int, slices: int, block_bytes: int) -> DataFrame:
    """(block, slice, keys, counts): each block's distinct grams, and words in the second half of the slices, with their counts in its training texts."""

    def kernel(batches):
        for block, _, held, texts in blocks_of(batches, block_bytes):
            train = [h is not True for h in held]
            for shift, (keys, counts) in ((0, counted_grams(texts, train, order)), (slices, counted_words(texts, train))):
                rows = by_slice(keys, slices)
                yield pa.record_batch(
                    [pa.array([block] * len(rows), pa.int64()), pa.array([shift + i for i, _ in rows], pa.int32()), pa.array([packed(keys[p]) for _, p in rows], pa.binary()), pa.array([packed(counts[p].astype(np.uint64)) for _, p in rows], pa.binary())],
                    names=["block", "slice", "keys", "counts"],
                )

    return map_batches(base.select("doc_id", "held_out", "text"), kernel, "block long, slice int, keys binary, counts binary")


def texts_by_blocks(base: DataFrame, block_bytes: int) -> DataFrame:
    """(block, doc_id, held_out, text): the documents under their blocks' numbers."""
    kind = base.schema["doc_id"].dataType

    def kernel(batches):
        from pyspark.sql.pandas.types import to_arrow_type

        for block, ids, held, texts in blocks_of(batches, block_bytes):
            for i in range(0, len(ids), 2048):
                part = slice(i, i + 2048)
                yield pa.record_batch(
                    [pa.array([block] * len(ids[part]), pa.int64()), pa.array(ids[part], to_arrow_type(kind)), pa.array(held[part], pa.bool_()), pa.array(texts[part], pa.binary()).cast(pa.string())], names=["block", "doc_id", "held_out", "text"]
                )

    return map_batches(base.select("doc_id", "held_out", "text"), kernel, f"block long, doc_id {kind.simpleString()}, held_out boolean, text string")


def merge_slices(asked: DataFrame, slices: int) -> DataFrame:
    """A row for each slice, without a block: its distinct keys in order and their counts in training texts; and a row for each block's asking: the places of its keys among them."""
    per = max(1, SPLITTER_SAMPLE // slices)

    def merge(table: pa.Table) -> pa.Table:
        slot = table["slice"][0].as_py()
        own = _unpacked(table["keys"])
        k, n = _merge(own, _unpacked(table["counts"]))
        with np.errstate(over="ignore"):
            some = k[np.argsort(k * _ODD * _ODD)[:per]] if slot < slices else k[:0]
        m = len(table)
        none = lambda kind: pa.nulls(m, kind)
        first = [[None], [len(k)], [int((n > 0).sum())], [int(n.sum())], [packed(k)], [packed(n.astype(np.uint64))], [some.tobytes()], [None]]
        rest = [table["block"].combine_chunks(), none(pa.int64()), none(pa.int64()), none(pa.int64()), none(pa.binary()), none(pa.binary()), none(pa.binary()), pa.array([packed(np.searchsorted(k, x).astype(np.uint32)) for x in own[1:]], pa.binary())]
        kinds = [pa.int64()] * 4 + [pa.binary()] * 4
        cols = [pa.chunked_array([pa.array(a, t), b], t) for a, b, t in zip(first, rest, kinds)]
        return pa.table([pa.array([slot] * (m + 1), pa.int32()), *cols], names=["slice", "block", "size", "known", "total", "keys", "counts", "sample", "places"])

    return asked.groupBy("slice").applyInArrow(merge, "slice int, block long, size long, known long, total long, keys binary, counts binary, sample binary, places binary")


def shared_counts(grams: DataFrame, splitters: np.ndarray, order: int) -> list[tuple]:
    """For each length below ``order`` the contexts that splitters cut, and their keys and counts: at most 257 keys for each of them."""
    across = spanning(splitters, order)

    def kernel(batches):
        held = [([np.empty(0, np.uint64)], [np.empty(0, np.int64)]) for _ in range(order)]
        for batch in batches:
            for keys, counts in zip(_unpacked(column(batch, "keys"))[1:], _unpacked(column(batch, "counts"))[1:]):
                g, n = keys[counts > 0], counts[counts > 0].astype(np.int64)
                for k in range(order):
                    context = context_at(g, k, order)
                    on = find(across[k], context) >= 0
                    held[k] = tuple([x] for x in _merge([*held[k][0], context[on] << _NINE | g[on] & _SYMBOL], [*held[k][1], n[on]]))
        for k, ((keys,), (n,)) in enumerate(held):
            yield pa.record_batch([pa.array(np.full(len(keys), k, np.int32)), pa.array(keys.view(np.int64)), pa.array(n)], names=["k", "key", "n"])

    found = map_batches(grams.select("keys", "counts"), kernel, "k int, key long, n long").groupBy("k", "key").agg(F.sum("n").alias("n")).toArrow()
    k, key, n = (found[c].to_numpy() for c in ("k", "key", "n"))
    out = []
    for level in range(order):
        keys, counts = _merge([key[k == level].view(np.uint64)], [n[k == level]])
        out.append((across[level], keys, counts))
    return out


def score_grams(grams: DataFrame, order: int, slices: int, shard_grams: int) -> DataFrame:
    """(slice, keys, values): the log10 probability of each distinct gram, by a trie that is dealt over tasks by range of context."""
    size = grams.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]
    sample = np.sort(np.concatenate([np.empty(0, np.uint64), *(np.frombuffer(bytes(r[0]), np.uint64) for r in grams.select("sample").toLocalIterator())])) >> _NINE
    shards = max(1, min(MOST_SHARDS, -(-size // shard_grams), len(sample)))
    splitters = np.unique(sample[[len(sample) * i // shards for i in range(1, shards)]]) if shards > 1 else sample[:0]
    told = shared_counts(grams, splitters, order)
    shared = grams.sparkSession.sparkContext.broadcast((splitters, told))

    def deal(batches):
        cuts = shared.value[0]
        for batch in batches:
            for keys, counts in zip(_unpacked(column(batch, "keys"))[1:], _unpacked(column(batch, "counts"))[1:]):
                # keys are in order, and so are their shards
                at = np.searchsorted(cuts, keys >> _NINE, "right")
                cut = np.searchsorted(at, np.arange(len(cuts) + 2))
                rows = [(i, a, b) for i, (a, b) in enumerate(zip(cut, cut[1:])) if b > a]
                yield pa.record_batch(
                    [pa.array([r[0] for r in rows], pa.int32()), pa.array([packed(keys[a:b]) for _, a, b in rows], pa.binary()), pa.array([packed(counts[a:b]) for _, a, b in rows], pa.binary())],
                    names=["shard", "keys", "counts"],
                )

    def score(table: pa.Table) -> pa.Table:
        cuts, told = shared.value
        shard = table["shard"][0].as_py()
        low = cuts[shard - 1] if shard else np.uint64(0)
        high = cuts[shard] if shard < len(cuts) else np.uint64(1 << BITS * order)
        near = []
        for k, (across, keys, n) in enumerate(told):  # of the contexts that several shards have, those that this one has
            shift = np.uint64(BITS * (order - k))
            context = keys >> _NINE
            on = (context >= low >> shift) & (context << shift < high)
            near.append((across, keys[on], n[on]))
        grams, counts = _merge(_unpacked(table["keys"]), _unpacked(table["counts"]))
        model = Trie(grams, counts, order, near)
        value = np.concatenate([np.empty(0), *(model.log10(grams[i : i + CHUNK]) for i in range(0, len(grams), CHUNK))])
        rows = by_slice(grams, slices)
        return pa.table({"slice": pa.array([i for i, _ in rows], pa.int32()), "keys": pa.array([packed(grams[p]) for _, p in rows], pa.binary()), "values": pa.array([packed(value[p]) for _, p in rows], pa.binary())})

    dealt = map_batches(grams.select("keys", "counts"), deal, "shard int, keys binary, counts binary")
    return dealt.groupBy("shard").applyInArrow(score, "slice int, keys binary, values binary")


def lm_scores(
    docs: DataFrame, by: int = 7, held: int = 2, order: int = ORDER, id_col: str = "doc_id", text_col: str = "text",
    shard_grams: int = SHARD_GRAMS, block_bytes: int = BLOCK_BYTES,
) -> DataFrame:
    """One row per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Training documents are those whose crc32 (of the id as text) modulo ``by`` isn't ``held``. ``score`` is the
    log10 probability of the whole text's bytes and its end under a trie of byte contexts up to
    ``order`` long that every training document has been counted into (contexts start anew with each document). The model is the same
    at every size: nothing that grows with the corpus is broadcast or held by one task. Documents go in blocks of about ``block_bytes``; a block asks
    once for each of its distinct grams and words. Askings meet by slices of their hash, where the corpus's distinct grams and their counts come out;
    these go to shards of the trie, about ``shard_grams`` each, whose ends may cut a context: such contexts' counts are summed beforehand and
    broadcast, at most 257 for each end and length. Answers go back by slice, then to the block, whose texts are read again. ``base_score`` is the sum over words
    (A to Z lower-cased) and one end of log10((c + 1) / (N + V + 1)). Words go by 64-bit hashes.

    Null text: the empty text, which has one token, its end. Null id: a training document. Repeated rows count and
    are scored each. No training documents: every symbol is one of 257, every word unknown. Empty table: no rows. Other columns are ignored.
    """
    if not 0 <= order <= 6:
        raise ValueError("contexts have 0 to 6 symbols")
    spark = docs.sparkSession
    base = fixed_rows(id_and_text(docs, id_col, text_col).withColumn("held_out", remainder(F.col("doc_id"), by) == held))
    volume = base.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    slices = max(SLICES, -(-volume // SLICE_BYTES))
    merged = materialise(merge_slices(asked_by_blocks(base, order, slices, block_bytes), slices), "merged")
    grams, words = (merged.filter(F.col("block").isNull() & on).drop("block", "places") for on in (F.col("slice") < slices, F.col("slice") >= slices))
    places = merged.filter("block IS NOT NULL").select("slice", "block", "places")
    tokens, kinds = words.agg(F.coalesce(F.sum("total"), F.lit(0)), F.coalesce(F.sum("known"), F.lit(0))).first()
    floor = math.log10(tokens + kinds + 1)

    def logs(batches):
        for batch in batches:
            values = [packed(np.log10(n.astype(np.float64) + 1)) for n in _unpacked(column(batch, "counts"))[1:]]
            yield pa.record_batch([column(batch, "slice"), column(batch, "keys"), pa.array(values, pa.binary())], names=["slice", "keys", "values"])

    answers = score_grams(grams, order, slices, shard_grams).unionByName(map_batches(words.select("slice", "keys", "counts"), logs, "slice int, keys binary, values binary"))

    def reply(asked: pa.Table, known: pa.Table) -> pa.Table:
        keys = np.concatenate(_unpacked(known["keys"]))
        values = np.concatenate([np.empty(0), *(unpacked(b, "<f8") for b in known["values"].to_pylist())])[np.argsort(keys)]
        kinds, codes = [], []
        for b in asked["places"].to_pylist():  # few values are different: each travels once, beside short codes
            different, code = np.unique(values[unpacked(b, "<u4")], return_inverse=True)
            kinds.append(different.tobytes())
            codes.append(packed(code.astype(np.uint16 if len(different) <= 1 << 16 else np.uint32)))
        return pa.table({"block": asked["block"], "slice": asked["slice"], "kinds": pa.array(kinds, pa.binary()), "codes": pa.array(codes, pa.binary())})

    replies = places.groupBy("slice").cogroup(answers.groupBy("slice")).applyInArrow(reply, "block long, slice int, kinds binary, codes binary")
    kind = base.schema["doc_id"].dataType.simpleString()

    def finish(mine: pa.Table, told: pa.Table) -> pa.Table:
        own = mine.combine_chunks()["text"].cast(pa.binary()).to_pylist()
        of = dict(zip(told["slice"].to_pylist(), zip(told["kinds"].to_pylist(), told["codes"].to_pylist())))

        def values_of(keys: np.ndarray, shift: int) -> np.ndarray:
            out = np.empty(len(keys))
            for i, p in by_slice(keys, slices):
                different = np.frombuffer(of[shift + i][0], np.float64)
                out[p] = different[unpacked(of[shift + i][1], "<u2" if len(different) <= 1 << 16 else "<u4")]
            return out

        keys, _ = counted_grams(own, [False] * len(own), order)
        values = values_of(keys, 0)
        score = np.zeros(len(own))
        for at, flat, lengths in pieces_of(own, order):
            log = values[np.searchsorted(keys, flat)]
            np.add.at(score, at, np.add.reduceat(log, np.cumsum([0, *lengths[:-1]])))
        there: set[bytes] = {b""}
        for text in own:
            for ws in words_of(text):
                there.update(ws)
        there = list(there)
        hashes = word_hashes(there)
        keys = np.unique(hashes)
        value = dict(zip(there, values_of(keys, slices)[np.searchsorted(keys, hashes)].tolist()))
        n_tokens, known, total = [], [], []
        for text in own:
            n, k, t = 1, 0, 0.0
            for ws in [*words_of(text), [b""]]:
                x = np.array([value[w] for w in ws])
                n, k, t = n + len(ws), k + int(np.count_nonzero(x)), t + float(x.sum())
            n_tokens.append(n - 1)
            known.append(k)
            total.append(t - (n - 1) * floor)
        return pa.table({
            "doc_id": mine["doc_id"], "held_out": mine["held_out"], "n_tokens": pa.array(n_tokens, pa.int64()), "n_known": pa.array(known, pa.int64()),
            "train_tokens": pa.array([int(tokens)] * len(own), pa.int64()), "base_score": pa.array(total, pa.float64()), "score": pa.array(score),
        })

    return texts_by_blocks(base, block_bytes).groupBy("block").cogroup(replies.groupBy("block")).applyInArrow(
        finish, f"doc_id {kind}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    )
