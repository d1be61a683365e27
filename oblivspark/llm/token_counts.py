"""Token counts by a broadcast table of frequent pre-tokens and a cache in each worker."""

from __future__ import annotations

import json
import unicodedata
import uuid
from collections import Counter
from itertools import groupby

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import column, id_and_text, map_batches, texts_of

#: Fixed value: the split that the byte-level vocabulary is defined with, white space and all.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Entries of the broadcast table; words that a task counts before it drops the rarer half, and that it hands on.
FREQUENT, COUNTED, HANDED = 1 << 16, 1 << 18, 1 << 12
#: Entries of a worker's cache of other pre-tokens; it is emptied when full.
CACHE = 1 << 18
#: Longer pre-tokens are encoded but never kept.
LONGEST = 64
#: First and last of the pictographs, which no version of Unicode has as letters, digits or blanks.
PICTOGRAPHS = (0x1F300, 0x1FAFF)


def odd_characters():
    """A pattern for the characters whose class may differ between versions of Unicode: those that aren't the same sort in an old and the present table."""
    old = unicodedata.ucd_3_2_0

    def sort(table, c: str) -> str:
        kind = table.category(c)
        return kind[0] if kind[0] in "LN" else "Z" if kind[0] == "Z" or c.isspace() else "C" if kind == "Cn" else "S"

    def steady(i: int) -> bool:
        if PICTOGRAPHS[0] <= i <= PICTOGRAPHS[1]:
            return True
        c = chr(i)
        return i < 0x10000 and not 0xD800 <= i < 0xE000 and (now := sort(unicodedata, c)) != "C" and now == sort(old, c) and bool(regex.match(r"\s", c)) == (now == "Z")

    runs = []
    for known, run in groupby(range(PICTOGRAPHS[1] + 1), steady):
        if known:
            run = list(run)
            runs.append(f"\\U{run[0]:08x}-\\U{run[-1]:08x}")
    return regex.compile(f"[^{''.join(runs)}]")


class Tokens:
    """Counts a text's tokens as the library does, from lengths of pre-tokens.

    Pre-tokens come from the vocabulary's own split where every character's class is the same in all versions of Unicode; any other
    text, and every text under a file that splits otherwise, goes to the library whole.
    """

    def __init__(self, path: str, frequent: dict[str, int]):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.frequent, self.lengths, self.room = frequent, dict(frequent), len(frequent) + CACHE
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        before, added = made.get("pre_tokenizer") or {}, made.get("added_tokens") or []
        self.split = (
            made.get("normalizer") is None and before.get("type") == "ByteLevel" and before.get("use_regex", True) and not before.get("add_prefix_space")
            and not any(t["single_word"] or t["lstrip"] or t["rstrip"] or t["normalized"] for t in added)
        )
        self.specials = [t["content"] for t in added]
        self.mark = regex.compile("|".join(regex.escape(s) for s in sorted(self.specials, key=len, reverse=True))) if self.specials else None
        self.find, self.odd = regex.compile(SPLIT).findall, odd_characters()

    def whole(self, text: str) -> int:
        return len(self.tokenizer.encode(text, add_special_tokens=False).ids)

    def length(self, piece: str) -> int:
        """Of a pre-token; kept while there is room."""
        n = self.whole(piece)
        if len(piece) <= LONGEST:
            if len(self.lengths) >= self.room:
                self.lengths = dict(self.frequent)
            self.lengths[piece] = n
        return n

    def count(self, text: str) -> int:
        if not self.split or not text.isascii() and self.odd.search(text):
            return self.whole(text)
        parts, extra = [text], 0
        if any(s in text for s in self.specials):
            parts = self.mark.split(text)
            extra = len(parts) - 1
        for part in parts:
            pieces = self.find(part)
            lengths = list(map(self.lengths.get, pieces))
            if None in lengths:
                lengths = [self.lengths.get(p) or self.length(p) if n is None else n for p, n in zip(pieces, lengths)]
            extra += sum(lengths)
        return extra


def frequent_words(base: DataFrame, size: int = FREQUENT) -> list[str]:
    """The ``size`` most frequent blank-parted words of all documents: each task counts its own and hands on at most ``HANDED``."""

    def kernel(batches):
        held: Counter = Counter()
        for batch in batches:
            for text in texts_of(batch):
                for at in range(0, len(text), 1 << 20):
                    held.update(text[at : at + (1 << 20)].split(b" "))
                if len(held) > COUNTED:
                    held = Counter(dict(held.most_common(COUNTED // 2)))
        top = [(w, n) for w, n in held.most_common(HANDED) if n > 1 and len(w) <= LONGEST]
        yield pa.record_batch([pa.array([w for w, _ in top], pa.binary()), pa.array([n for _, n in top], pa.int64())], names=["word", "n"])

    told = map_batches(base.select("text"), kernel, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return [bytes(r[0]).decode(errors="ignore") for r in told.orderBy(F.desc("n"), "word").limit(size).toLocalIterator()]


def frequent_lengths(base: DataFrame, path: str, size: int = FREQUENT) -> dict[str, int]:
    """Lengths of the pre-tokens of the corpus's most frequent words, at most ``size`` of them."""
    tokens = Tokens(path, {})
    if not tokens.split:
        return {}
    out: dict[str, int] = {}
    for word in frequent_words(base, size):
        for piece in tokens.find(" " + word):
            if len(out) < size and piece not in out and len(piece) <= LONGEST and not tokens.odd.search(piece):
                out[piece] = tokens.whole(piece)
    return out


def pack(table: dict[str, int]) -> tuple[bytes, bytes]:
    """The table as two byte strings: the pre-tokens, parted by a byte that UTF-8 never has, and their lengths."""
    kept = {p: n for p, n in table.items() if n < 256}
    return b"\xff".join(p.encode() for p in kept), bytes(kept.values())


def unpack(packed: tuple[bytes, bytes]) -> dict[str, int]:
    return dict(zip((p.decode() for p in packed[0].split(b"\xff")), packed[1])) if packed[1] else {}


_workers: dict[str, Tokens] = {}


def token_counts(docs: DataFrame, path: str, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_bytes, n_tokens, over_limit (more than ``limit`` tokens).

    Counts what the tokenizer file at ``path`` gives for the whole text
    without added tokens; special strings inside a text are one token each. Where the file is byte-level BPE with the usual split, a text is split as
    the library would, each piece's length comes from the broadcast table of the corpus's frequent pre-tokens, else from the worker's cache, else
    from the library. Texts with characters whose class depends on the version of Unicode, and files of another kind, are encoded whole. Words are
    counted in each task, of which each hands on a bounded number; pre-tokens are never exchanged. The table's and the cache's sizes don't grow with the input, and neither has a say in the result.

    Null or empty text: 0 bytes, 0 tokens. Null or repeated ids, ties: one row for each input
    row. Empty table: no rows. Other columns are ignored.
    """
    base = id_and_text(docs, id_col, text_col)
    shared = docs.sparkSession.sparkContext.broadcast(pack(frequent_lengths(base, path)))
    key = uuid.uuid4().hex

    def kernel(batches):
        if key not in _workers:
            _workers.clear()
            _workers[key] = Tokens(path, unpack(shared.value))
        count = _workers[key].count
        for batch in batches:
            texts = texts_of(batch)
            counts = [count(t.decode()) for t in texts]
            yield pa.record_batch(
                [column(batch, "doc_id"), pa.array([len(t) for t in texts], pa.int64()), pa.array(counts, pa.int64()), pa.array([n > limit for n in counts], pa.bool_())],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    kind = base.schema["doc_id"].dataType.simpleString()
    return map_batches(base, kernel, f"doc_id {kind}, n_bytes long, n_tokens long, over_limit boolean")
