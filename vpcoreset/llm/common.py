"""What the training-data operators share: scratch folders, word hashing and grouped batches."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

#: Words are maximal runs of characters other than space, tab, LF, VT, FF and CR.
WORD = r"[^\x20\x09-\x0D]+"
#: Bytes hashed at once; bounds the memory of a Python worker whatever the length of a text.
PIECE = 1 << 20
_ODD = np.uint64(0x9E3779B97F4A7C15)


#: Rows of an Arrow batch; with texts of some kilobytes a batch takes a few megabytes on either side.
BATCH_ROWS = 2_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder that the session names; without one, a temporary folder in local mode, as in tests, and an error on a cluster."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isEmpty():
            if not spark.sparkContext.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="vpcoreset-"))
            held = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = held.get()
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it back: the plan is cut and lost executors cost no recomputation."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def trimmed(f):
    """Batch function f; when it has ended, memory that it used goes back to the system, since workers live on."""

    def run(batches: Iterator) -> Iterator:
        yield from f(batches)
        gc.collect()
        try:
            ctypes.CDLL(None).malloc_trim(0)
        except (AttributeError, OSError):
            pass

    return run


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over 64 output bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE = np.arange(256, dtype=np.uint8)
_SPACE = np.isin(_BYTE, [32, 9, 10, 11, 12, 13])
_LOWER = np.where((_BYTE >= 65) & (_BYTE <= 90), _BYTE + 32, _BYTE).astype(np.uint8)
_RANDOM = mix64(np.arange(1, 257, dtype=np.uint64) * _ODD)
_POWERS = np.cumprod(np.concatenate([[np.uint64(1)], np.full(4095, np.uint64(0xD6E8FEB86659FD93))]))


def _hash_piece(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Hash and first byte of each word of a piece."""
    raw = np.frombuffer(data, np.uint8)
    word = ~_SPACE[raw]
    edge = np.diff(np.concatenate([[False], word, [False]]).astype(np.int8))
    start, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    if not len(start):
        return np.zeros(0, np.uint64), start
    at = np.flatnonzero(word)
    offset = at - np.repeat(start, end - start)
    coded = _RANDOM[_LOWER[raw[at]]] * (_POWERS[offset & 4095] + (offset >> 12).astype(np.uint64))
    first = np.cumsum(end - start) - (end - start)
    return mix64(np.add.reduceat(coded, first) + (end - start).astype(np.uint64)), start


def _pieces(data: bytes) -> Iterator[bytes]:
    """Cut a long text at white space; a word longer than a piece stays whole."""
    at = 0
    while len(data) - at > PIECE:
        cut = max(data.rfind(b" ", at, at + PIECE), data.rfind(b"\n", at, at + PIECE))
        if cut <= at:
            after = [x for x in (data.find(b" ", at + PIECE), data.find(b"\n", at + PIECE)) if x >= 0]
            cut = min(after, default=len(data))
        yield data[at:cut]
        at = cut
    yield data[at:]


def hash_texts(texts: Iterable[str | None]) -> Iterator[np.ndarray]:
    """For each text, the 64-bit hashes of its words (letters A-Z count as a-z); null counts as empty."""
    held: list[bytes] = []
    size = 0

    def flush() -> Iterator[np.ndarray]:
        lengths = np.array([len(x) + 1 for x in held])
        hashes, start = _hash_piece(b"\n".join(held))
        ends = np.searchsorted(start, np.cumsum(lengths))
        return iter(np.split(hashes, ends[:-1]))

    for text in texts:
        data = text.encode("utf-8", "surrogatepass") if text else b""
        if size + len(data) > PIECE and held:
            yield from flush()
            held, size = [], 0
        if len(data) > PIECE:
            yield np.concatenate([_hash_piece(x)[0] for x in _pieces(data)])
        else:
            held.append(data)
            size += len(data) + 1
    if held:
        yield from flush()


def shingles(words: np.ndarray, width: int) -> np.ndarray:
    """Sorted distinct hashes of the runs of ``width`` words; a shorter text is one run, an empty one has none."""
    if not len(words):
        return words
    if len(words) < width:
        words, width = words[None, :].copy(), words.shape[0]
        run = np.zeros(1, np.uint64)
        for i in range(width):
            run = mix64(run * _ODD + words[:, i])
        return run
    n = len(words) - width + 1
    run = np.zeros(n, np.uint64)
    for i in range(width):
        run = mix64(run * _ODD + words[i : i + n])
    return np.unique(run)


def groups(batches: Iterable[pd.DataFrame], keys: list[str]) -> Iterator[pd.DataFrame]:
    """Whole groups from batches that are sorted by keys; a group may cross batches."""
    held: list[pd.DataFrame] = []
    for batch in batches:
        if not len(batch):
            continue
        codes = np.zeros(len(batch), bool)
        for k in keys:
            v = batch[k].to_numpy()
            codes[1:] |= v[1:] != v[:-1]
        if held and all(held[-1][k].iloc[-1] == batch[k].iloc[0] for k in keys):
            first = True
        else:
            first = False
            if held:
                yield pd.concat(held, ignore_index=True) if len(held) > 1 else held[0]
                held = []
        cuts = [0, *np.flatnonzero(codes).tolist(), len(batch)]
        for i, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
            part = batch.iloc[a:b]
            if i == 0 and first:
                held.append(part)
            else:
                if held:
                    yield pd.concat(held, ignore_index=True) if len(held) > 1 else held[0]
                held = [part]
    if held:
        yield pd.concat(held, ignore_index=True) if len(held) > 1 else held[0]
