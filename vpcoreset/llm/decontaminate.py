"""Benchmark decontamination with spaced seeds.

A seed is a fixed mask over a run of words: only its selected positions are hashed, so a hit survives
substituted words at the ignored ones. All hashes of the test items form a table that is joined with
the hashes of the documents; each hit names a diagonal (document position less item position), along which
the item is compared word by word, without gaps. A stretch is a leak if ``identity`` of its words are equal and it
holds enough of them: ``min_match``, or ``identity`` of the words of a shorter item. The best stretch (matches +1,
mismatches -3) is reported where it holds ``min_match`` or all words of the item, otherwise the stretch with the most equal words.

The test items are taken in blocks of at most ``block_chars`` characters. A block's table is broadcast, meets all
documents, and is given up before the next one: broadcasts are bounded, each and in sum, whatever the size of the test set.

Defined results: null or empty texts and items leak nothing; items of fewer than five words are no evidence and
match nothing; of several stretches of one item in one document the longest is reported, ties to the
earliest; repeated rows are reported each; columns other than ids and texts are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset.llm.common import mix64, stored, trimmed

# Selected positions of each mask. The first spares every 5th, 6th or 7th word, the second every 4th, the third every 3rd.
MASKS = ((0, 1, 2, 3, 5, 6), (0, 1, 2, 4, 5, 6), (0, 1, 3, 4, 6, 7), (0, 1, 3, 6, 7, 9))
#: Further masks, with the most words of the items that they are for: together they find every item of 5 to 22 words of which a fifth is substituted, wherever.
SHORT = ((20, (0, 1, 2, 3, 4)), (20, (0, 1, 2, 4, 6)), (8, (0, 1, 2, 3)), (8, (0, 1, 2, 4)), (8, (0, 1, 3, 4)), (8, (0, 2, 3, 4)))
EDGES = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~«»„“”‘’…¡¿"
SCHEMA = "doc string, item string, doc_start int, doc_end int, item_start int, item_end int, n_match int, identity double"
#: Words that a task remembers; others are looked up each time.
MEMO = 1 << 17
#: Words that are hashed together, and bits of the table that tells at once that a hash is no item's.
AT_ONCE, FILTER = 1 << 16, 22


class Vocabulary(dict):
    """Number of a raw word: that of the items' word, 0 for others, -1 for punctuation alone."""

    def __init__(self, words: dict[str, int]):
        super().__init__()
        self.words = words

    def __missing__(self, raw: str) -> int:
        word = raw.lower().strip(EDGES)
        n = self.words.get(word, 0) if word else -1
        if len(self) < MEMO:
            self[raw] = n
        return n

    def read(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the words of a text and their places among its white-space words."""
        raw = text.split() if text else []
        n = np.fromiter(map(self.__getitem__, raw), np.int64, len(raw))
        at = np.flatnonzero(n >= 0)
        return n[at], at


_ODD = np.uint64(0x9E3779B97F4A7C15)


def seed_hashes(words: np.ndarray, mask: tuple[int, ...], no: int) -> tuple[np.ndarray, np.ndarray]:
    """Places at which all selected words belong to the vocabulary, and their hashes; hits are compared word by word, so a collision costs time alone."""
    n = len(words) - mask[-1]
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    known, value = words > 0, words.astype(np.uint64)
    good, h = np.ones(n, bool), np.full(n, no + 1, np.uint64)
    for p in mask:
        good &= known[p : p + n]
        h = h * _ODD + value[p : p + n]
    at = np.flatnonzero(good)
    return at, mix64(h[at])


def masks_for(words: int) -> list[tuple[int, ...]]:
    """The masks of an item of so many words; those of longer items come first."""
    return [*MASKS, *[mask for most, mask in SHORT if words <= most]]


def build_index(items: list[tuple[int, str]]) -> dict:
    """Words and seed table of a block of test items."""
    names: dict[str, int] = {}
    plain = [[w for w in (x.lower().strip(EDGES) for x in (text or "").split()) if w] for _, text in items]
    coded = [np.array([names.setdefault(w, len(names) + 1) for w in words], np.int64) for words in plain]
    h, item, place = [], [], []
    for i, words in enumerate(coded):
        if len(words) < 5:
            continue
        for no, mask in enumerate(masks_for(len(words))):
            at, x = seed_hashes(words, mask, no)
            h.append(x)
            item.append(np.full(len(x), i))
            place.append(at)
    h = np.concatenate(h) if h else np.zeros(0, np.uint64)
    order = np.argsort(h, kind="stable")
    seen = np.zeros(1 << FILTER, bool)
    seen[h & np.uint64((1 << FILTER) - 1)] = True
    return {
        "seen": seen,
        "names": names, "ids": [i for i, _ in items], "coded": coded, "masks": masks_for(min((len(c) for c in coded if len(c) >= 5), default=99)),
        "hash": h[order], "item": (np.concatenate(item) if item else np.zeros(0, int))[order], "place": (np.concatenate(place) if place else np.zeros(0, int))[order],
    }


def best_stretch(equal: np.ndarray) -> tuple[int, int]:
    """Start and end of the run with the largest sum, a match counting 1 and a mismatch -3."""
    total = np.concatenate([[0], np.cumsum(np.where(equal, 1, -3))])
    lowest = np.minimum.accumulate(total)
    end = int(np.argmax(total - lowest))
    start = int(np.argmax(total[: end + 1] == lowest[end]))
    return start, end


def longest_stretch(equal: np.ndarray, identity: float) -> tuple[int, int]:
    """Start and end of the stretch with the most equal words of which ``identity`` of the words are equal; between equal words, or empty."""
    total = np.concatenate([[0], np.cumsum(equal)])
    level = total - identity * np.arange(len(total))
    start = np.searchsorted(-np.minimum.accumulate(level), -level - 1e-9, "left")
    end = int(np.argmax(total - total[start]))
    at = np.flatnonzero(equal[start[end] : end]) + start[end]
    return (int(at[0]), int(at[-1]) + 1) if len(at) else (0, 0)


def leaks(text: str | None, index: dict, vocabulary: Vocabulary, min_match: int, identity: float) -> Iterator[tuple]:
    """(item number, document start and end in white-space words, item start and end, matches, identity) of one text."""
    for _, *found in leaks_of([text], index, vocabulary, min_match, identity):
        yield tuple(found)


def leaks_of(texts: list[str | None], index: dict, vocabulary: Vocabulary, min_match: int, identity: float) -> Iterator[tuple]:
    """(number of the text, and what ``leaks`` gives) of many texts, whose words are hashed together in runs of about AT_ONCE."""
    low = 0
    while low < len(texts):
        read, size, up = [], 0, low
        while up < len(texts) and size < AT_ONCE:
            read.append(vocabulary.read(texts[up]))
            size += len(read[-1][0])
            up += 1
        for k, found in _leaks_together(read, index, min_match, identity):
            yield (low + k, *found)
        low = up


def _leaks_together(read: list[tuple[np.ndarray, np.ndarray]], index: dict, min_match: int, identity: float) -> Iterator[tuple]:
    gap = np.zeros(max(m[-1] for m in index["masks"]) + 1, np.int64)  # no seed reaches from text to text
    first = np.cumsum([0, *[len(w) + len(gap) for w, _ in read]])
    words = np.concatenate([x for w, _ in read for x in (w, gap)])
    low_bits = np.uint64((1 << FILTER) - 1)
    diagonals: dict[int, set[tuple[int, int]]] = {}
    for no, mask in enumerate(index["masks"]):
        where, h = seed_hashes(words, mask, no)
        some = np.flatnonzero(index["seen"][h & low_bits])
        where, h = where[some], h[some]
        left, right = np.searchsorted(index["hash"], h, "left"), np.searchsorted(index["hash"], h, "right")
        hit = np.flatnonzero(right > left)
        for k, at in zip((np.searchsorted(first, where[hit], "right") - 1).tolist(), hit.tolist(), strict=True):
            own = slice(left[at], right[at])
            diagonals.setdefault(k, set()).update(zip(index["item"][own].tolist(), (int(where[at] - first[k]) - index["place"][own]).tolist(), strict=True))
    for k, own in sorted(diagonals.items()):
        for found in _verified(*read[k], own, index, min_match, identity):
            yield k, found


def _verified(words: np.ndarray, at: np.ndarray, diagonals: set[tuple[int, int]], index: dict, min_match: int, identity: float) -> Iterator[tuple]:
    """The best leak of each item along the diagonals of a text."""
    best: dict[int, tuple] = {}
    for item, shift in sorted(diagonals):
        coded = index["coded"][item]
        a, b = max(0, -shift), min(len(coded), len(words) - shift)
        equal = words[a + shift : b + shift] == coded[a:b]
        s, e = best_stretch(equal)
        n = int(equal[s:e].sum())
        if n < min(min_match, len(coded)) or n < identity * (e - s):
            s, e = longest_stretch(equal, identity)
            n = int(equal[s:e].sum())
            if n < min(min_match, math.ceil(identity * len(coded) - 1e-9)):
                continue
        if item not in best or n > best[item][4]:
            best[item] = (int(at[s + a + shift]), int(at[e - 1 + a + shift]) + 1, s + a, e + a, n, n / (e - s))
    for item, found in best.items():
        yield item, *found


def _blocks(spark, benchmark: DataFrame, item_col: str, text_col: str, block_chars: int) -> Iterator[tuple]:
    """(broadcast index, whether it is the only one) for each block of test items of about ``block_chars`` characters."""
    items = benchmark.select(F.col(item_col).cast("string").alias("item"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    chars = items.agg(F.sum(F.length("text") + 16)).collect()[0][0] or 0
    blocks = -(-chars // block_chars) or 1
    for block in range(blocks):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == block)
        yield spark.sparkContext.broadcast(build_index(sorted(((r["item"], r["text"]) for r in part.collect()), key=lambda x: (x[0] is None, x[0] or "", x[1])))), blocks == 1


def find_leaks(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text",
               min_match: int = 10, identity: float = 0.8, block_chars: int = 8_000_000) -> DataFrame:
    """One row for each document and test item that share a leak."""
    rows = docs.select(F.col(id_col).cast("string").alias("doc"), F.col(text_col).alias("text"))
    out = None
    for held, only in _blocks(docs.sparkSession, benchmark, item_col, item_text_col, block_chars):

        def search(batches: Iterator[pd.DataFrame], held=held) -> Iterator[pd.DataFrame]:
            index = held.value
            vocabulary = Vocabulary(index["names"])
            for batch in batches:
                docs_ = batch["doc"].tolist()
                found = [(docs_[k], index["ids"][item], *rest) for k, item, *rest in leaks_of(batch["text"].tolist(), index, vocabulary, min_match, identity)]
                if found:
                    yield pd.DataFrame(found, columns=["doc", "item", "doc_start", "doc_end", "item_start", "item_end", "n_match", "identity"])

        found = rows.mapInPandas(trimmed(search), SCHEMA)
        if not only:  # one block at a time: its leaks are written, its table is given up
            found = stored(found, "leaks")
            held.destroy()
        out = found if out is None else out.unionByName(found)
    return out.select(
        F.col("doc").cast(docs.schema[id_col].dataType).alias(id_col), F.col("item").cast(benchmark.schema[item_col].dataType).alias(item_col),
        "doc_start", "doc_end", "item_start", "item_end", "n_match", "identity")


def drop_leaking(docs: DataFrame, benchmark: DataFrame, *, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text",
                 min_match: int = 10, identity: float = 0.8, block_chars: int = 8_000_000) -> DataFrame:
    """The rows of docs, all columns, that share a leak with no test item."""
    for held, only in _blocks(docs.sparkSession, benchmark, item_col, item_text_col, block_chars):

        def keep(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            index = held.value
            vocabulary = Vocabulary(index["names"])
            for batch in batches:
                clean = np.ones(batch.num_rows, bool)
                clean[[k for k, *_ in leaks_of(batch.column(text_col).to_pylist(), index, vocabulary, min_match, identity)]] = False
                yield batch.filter(pa.array(clean))

        docs = docs.mapInArrow(trimmed(keep), docs.schema)
        if not only:
            docs = stored(docs, "without-leaks")
            held.destroy()
    return docs
