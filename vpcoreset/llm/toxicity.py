"""Toxicity by maximum-scoring segments of token log-odds.

Tokens are white-space words in lower case without punctuation at their ends. A labelled sample
gives, for each token, the number of toxic and other documents that hold it. Its odds are those of
a Dirichlet posterior whose prior is the posterior of the token's stem (the first four letters),
whose prior in turn is the share of toxic documents; so unseen inflections of a toxic stem count.
A token scores its log-odds against that share, less a drift that makes ordinary text negative, at each of its places;
in the evidence for the document a token of the passages counts once.

A linear scan finds all maximal segments of positive total. A segment of score S in n tokens has
the expectation ``E = K n exp(-lambda S)`` in ordinary text: lambda solves the moment equation on
the token scores of clean documents, K fits the largest segments of clean documents. Segments with
E below ``significance`` are passages; a logistic curve, fitted on documents that had no part in
the odds, turns the sum of their ``-ln E`` into a probability.

Bound: the odds and the curve are fitted on at most ``sample`` labelled rows (by hash of the id), one
half each; all documents are scored, and whole.

Defined results: null and empty texts have no passage and the curve's lowest score; without any
usable labels every score is 0; of labels of one id that differ the toxic one counts; repeated rows are scored alike, each; columns other than id and text
are ignored; texts of any length are scanned whole.
"""

from __future__ import annotations

import hashlib
import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset.llm.common import stored, trimmed

STEM, STEM_WEIGHT, TOKEN_WEIGHT, DRIFT, TOP = 4, 12.0, 4.0, 1.5, 6.0
EDGES = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~«»„“”‘’…¡¿"
SCHEMA = "id string, score double, predicted int, passages array<struct<start:int,end:int,score:double,evalue:double>>"
#: Tokens that a task remembers; others are worked out each time.
MEMO = 1 << 17
#: A longer token is known by its first letters and a digest of the whole.
LONGEST = 64


def plain(raw: str) -> str:
    """The token of a raw word: lower case, no punctuation at its ends, bounded in length."""
    word = raw.lower().strip(EDGES)
    if len(word) <= LONGEST:
        return word
    return word[: LONGEST - 32] + hashlib.blake2b(word.encode("utf-8", "surrogatepass"), digest_size=16).hexdigest()


def maximal_segments(scores: list[tuple[int, int, float]]) -> list[tuple[int, int, float]]:
    """All maximal scoring segments of runs (start, end, total), in linear time.

    Every candidate keeps the running total on its left and its right side. A new positive run is
    merged with the latest candidate of smaller left total as long as that one's right total is smaller, too.
    """
    total, held = 0.0, []  # of (start, end, left, right, candidate to look at before it)
    for start, end, value in scores:
        left, total = total, total + value
        if value <= 0:
            continue
        new, right = start, total
        back = len(held) - 1
        while True:
            while back >= 0 and held[back][2] >= left:
                back = held[back][4]
            if back < 0 or held[back][3] >= right:
                held.append((new, end, left, right, back))
                break
            new, left = held[back][0], held[back][2]
            back_next = held[back][4]
            del held[back:]
            back = back_next
    return [(a, b, right - left) for a, b, left, right, _ in held]


class TokenScores(dict):
    """Score of a raw token; unknown ones are worked out once and remembered."""

    def __init__(self, tokens: dict[str, float], stems: dict[str, float]):
        super().__init__()
        self.tokens, self.stems = tokens, stems

    def __missing__(self, raw: str) -> float:
        word = plain(raw)
        known = self.tokens.get(word)
        value = known if known is not None else self.stems.get(word[:STEM], 0.0)
        if len(self) < MEMO:
            self[raw] = value
        return value


def runs(text: str | None, look: TokenScores) -> tuple[int, list[tuple[int, int, float]], np.ndarray]:
    """Number of tokens, the runs of a text (scored tokens one by one, the others together) and its token scores; those without score drift down."""
    words = text.split() if text else []
    value = np.fromiter(map(look.__getitem__, words), float, len(words))
    out, at = [], 0
    for i in np.flatnonzero(value).tolist():
        if i > at:
            out.append((at, i, -DRIFT * (i - at)))
        out.append((i, i + 1, float(value[i])))
        at = i + 1
    return len(words), out, value


def _counts(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for batch in batches:
        seen: tuple[Counter, Counter] = (Counter(), Counter())
        for text, toxic in zip(batch["text"], batch["toxic"], strict=True):
            words = {x for w in set((text or "").split()) if (x := plain(w))}
            seen[toxic].update(words)
            seen[toxic].update({"\0" + w[:STEM] for w in words})
        words = list(seen[0].keys() | seen[1].keys())
        if words:
            yield pd.DataFrame({"token": words, "toxic": [seen[1][w] for w in words], "other": [seen[0][w] for w in words]})


def _logit(p: float) -> float:
    return math.log(p / (1 - p))


def fit(docs: DataFrame, labels: DataFrame, *, sample: int = 20_000, significance: float = 0.05) -> dict:
    """Model from (id, text) rows and (id, toxic) labels."""
    empty = {"tokens": {}, "stems": {}, "lambda": 1.0, "K": 1.0, "curve": (-30.0, 0.0), "significance": significance}
    chosen = labels.where(F.col("toxic").isin(0, 1) & F.col("id").isNotNull()).groupBy("id").agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = chosen.orderBy(F.xxhash64("id"), "id").limit(sample).withColumn("half", F.pmod(F.xxhash64("id", F.lit(7)), F.lit(2)))
    rows = stored(docs.select("id", "text").join(F.broadcast(chosen), "id"), "toxic-sample")
    size = {(r["half"], r["toxic"]): r["n"] for r in rows.groupBy("half", "toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    n1, n0 = size.get((0, 1), 0), size.get((0, 0), 0)
    if not n1 or not n0:
        return empty
    share = n1 / (n1 + n0)
    counts = rows.where(F.col("half") == 0).select("text", "toxic").mapInPandas(trimmed(_counts), "token string, toxic long, other long")
    counts = counts.groupBy("token").agg(F.sum("toxic").alias("toxic"), F.sum("other").alias("other"))
    is_stem = F.col("token").startswith("\0")
    stems = counts.where(is_stem).select(F.substring("token", 2, STEM).alias("stem"), ((F.col("toxic") + STEM_WEIGHT * share) / (F.col("toxic") + F.col("other") + STEM_WEIGHT)).alias("p"))
    tokens = counts.where(~is_stem).withColumn("stem", F.substring("token", 1, STEM)).join(stems, "stem")
    tokens = tokens.select("token", "stem", "p", ((F.col("toxic") + TOKEN_WEIGHT * F.col("p")) / (F.col("toxic") + F.col("other") + TOKEN_WEIGHT)).alias("q"))
    high = 1 / (1 + math.exp(-(_logit(share) + DRIFT)))
    # What is not kept scores as its stem; at most as many rows as the bounded sample has tokens.
    kept = tokens.where((F.col("q") > high) | (F.col("p") > high)).collect()
    worth = lambda p: min(_logit(p) - _logit(share), TOP) - DRIFT
    model = empty | {
        "stems": {r["stem"]: worth(r["p"]) for r in stems.where(F.col("p") > high).collect()},
        "tokens": {r["token"]: worth(r["q"]) for r in kept},
    }
    # Calibration on the other half.
    clean = rows.where((F.col("half") == 1) & (F.col("toxic") == 0)).select("text")

    def histogram(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        look = TokenScores(model["tokens"], model["stems"])
        for batch in batches:
            tally: Counter = Counter()
            for text in batch["text"]:
                n, _, value = runs(text, look)
                some = value[value != 0]
                tally[-DRIFT] += n - len(some)
                tally.update(np.round(some, 2).tolist())
            yield pd.DataFrame({"value": list(tally.keys()), "n": list(tally.values())})

    tally = {r["value"]: r["n"] for r in clean.mapInPandas(histogram, "value double, n long").groupBy("value").agg(F.sum("n").alias("n")).collect()}
    tally[TOP - DRIFT] = tally.get(TOP - DRIFT, 0) + 1  # never certain that clean text lacks the worst token
    value, weight = np.array(list(tally)), np.array(list(tally.values()), float)
    weight /= weight.sum()
    low, up = 1e-3, 3.0
    for _ in range(60):
        mid = (low + up) / 2
        low, up = (mid, up) if (weight * np.exp(mid * value)).sum() < 1 else (low, mid)
    model["lambda"] = low

    def largest(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        look = TokenScores(model["tokens"], model["stems"])
        for batch in batches:
            found = [runs(text, look)[:2] for text in batch["text"]]
            yield pd.DataFrame({"docs": [len(found)], "mass": [sum(n * math.exp(-low * max([0.0, *(s for *_, s in maximal_segments(r))])) for n, r in found)]})

    k = clean.mapInPandas(largest, "docs long, mass double").agg(F.sum("docs").alias("docs"), F.sum("mass").alias("mass")).collect()[0]
    model["K"] = (k["docs"] or 1) / max(k["mass"] or 1.0, 1.0)

    def evidence(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        look = TokenScores(model["tokens"], model["stems"])
        for batch in batches:
            yield pd.DataFrame({"x": [_evidence(text, passages(text, model, look), model, look) for text in batch["text"]], "y": batch["toxic"].astype(float)})

    pairs = rows.where(F.col("half") == 1).select("text", "toxic").mapInPandas(evidence, "x double, y double").toPandas()
    model["curve"] = _curve(pairs["x"].to_numpy(), pairs["y"].to_numpy()) if len(pairs) else (-30.0, 0.0)
    return model


def passages(text: str | None, model: dict, look: TokenScores) -> list[tuple[int, int, float, float]]:
    """(first token, end, score, E) of every significant segment."""
    n, found, _ = runs(text, look)
    out = []
    for a, b, s in maximal_segments(found):
        e = model["K"] * n * math.exp(-model["lambda"] * s)
        if e < model["significance"]:
            out.append((a, b, s, e))
    return out


def _evidence(text: str | None, found: list[tuple[int, int, float, float]], model: dict, look: TokenScores) -> float:
    """Evidence of the passages of a text; a token that an earlier place in them holds counts as ordinary text, since odds are by document."""
    if not found:
        return 0.0
    words, told, total = text.split(), set(), 0.0
    for a, b, s, _ in found:
        for raw in words[a:b]:
            if value := look[raw]:
                if (word := plain(raw)) in told:
                    s -= value + DRIFT
                told.add(word)
        e = model["K"] * len(words) * math.exp(-model["lambda"] * s) if s > 0 else 1.0
        total += max(0.0, -math.log(max(e, 1e-300))) if e < model["significance"] else 0.0
    return math.log1p(total)


def _curve(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Logistic fit of one variable with a light ridge, by Newton steps; the slope is not negative."""
    a, b = _logit(min(max(y.mean(), 1e-4), 1 - 1e-4)), 0.1
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a + b * x, -30, 30)))
        w = p * (1 - p) + 1e-9
        grad = np.array([(y - p).sum() - 0.01 * a, ((y - p) * x).sum() - 0.01 * b])
        hess = np.array([[w.sum() + 0.01, (w * x).sum()], [(w * x).sum(), (w * x * x).sum() + 0.01]])
        step = np.clip(np.linalg.solve(hess, grad), -2, 2)
        a, b = a + step[0], b + step[1]
        if np.abs(step).max() < 1e-8:
            break
    return float(a), float(max(b, 0.0))


def score_toxicity(docs: DataFrame, model: dict, *, threshold: float = 0.3) -> DataFrame:
    """(id, score, predicted, passages) of every row of (id, text)."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m = held.value
        look = TokenScores(m["tokens"], m["stems"])
        a, b = m["curve"]
        for batch in batches:
            found = [passages(text, m, look) for text in batch["text"]]
            value = np.array([1 / (1 + math.exp(-max(-30.0, min(30.0, a + b * _evidence(t, f, m, look))))) for t, f in zip(batch["text"], found, strict=True)]) if m["tokens"] or m["stems"] else np.zeros(len(found))
            yield pd.DataFrame({
                "id": batch["id"], "score": value, "predicted": (value >= threshold).astype("int32"),
                "passages": [[{"start": p[0], "end": p[1], "score": p[2], "evalue": p[3]} for p in f] for f in found],
            })

    return docs.select("id", "text").mapInPandas(trimmed(score), SCHEMA)


def toxicity(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample: int = 20_000, threshold: float = 0.3) -> DataFrame:
    """Learns from the labels whose crc32(id) mod 4 is not 2 and scores every document."""
    rest = lambda c: F.pmod(F.crc32(F.col(c).cast("string")), F.lit(4))
    known = labels.where(rest(id_col) != 2).select(F.col(id_col).alias("id"), F.col(label_col).alias("toxic"))
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    model = fit(rows, known, sample=sample)
    scored = score_toxicity(rows.withColumn("id", F.col("id").cast("string")), model, threshold=threshold).withColumn("id", F.col("id").cast(docs.schema[id_col].dataType))
    return scored.select(F.col("id").alias(id_col), F.coalesce(rest("id") == 2, F.lit(False)).alias("held_out"), "score", "predicted", "passages")


def reject_toxic(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample: int = 20_000, threshold: float = 0.3) -> DataFrame:
    """The rows of docs, all columns, whose score is below the threshold; labels are used as by ``toxicity``."""
    known = labels.where(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(4)) != 2).select(F.col(id_col).alias("id"), F.col(label_col).alias("toxic"))
    model = fit(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), known, sample=sample)
    held = docs.sparkSession.sparkContext.broadcast(model)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        look = TokenScores(m["tokens"], m["stems"])
        a, b = m["curve"]
        some = bool(m["tokens"] or m["stems"])
        for batch in batches:
            texts = batch.column(text_col).to_pylist()
            yield batch.filter(pa.array([not some or 1 / (1 + math.exp(-max(-30.0, min(30.0, a + b * _evidence(t, passages(t, m, look), m, look))))) < threshold for t in texts], pa.bool_()))

    return docs.mapInArrow(trimmed(keep), docs.schema)
