"""Document log-likelihood under a gated recurrent language model, beside a unigram base.

Tokens are white-space words with A-Z in lower case, then one end of text. Counts cover all training documents.
The vocabulary has three parts: the ``HEAD`` most frequent words, each with a vector and a place in a class of the
network's output; words of at least a count that at most ``held`` words reach, whose counts are broadcast; and
all others, whose counts meet them in a join. Tail words (the second and third part) belong to classes that
are ranges of spelling of about equal mass. The network gives the probability of a class in context; inside a tail
class a word has its count less an absolute discount, and the discounts of a class are the probability of any word
that training has not seen, which counts as one event there (the base has one such event, too).

Words are looked up once: a pass over the texts stores the codes of their tokens (two bytes each), which training and
scoring read, with all that needs no network: counts of tokens, base scores, probabilities inside classes.

Training: all training documents are dealt to ``rounds`` rounds by a hash, each to one of them. The texts of a round
are read in windows by all tasks at once, from common parameters; after a round the parameters are
averaged, weighted by tokens, in a tree. Memory: a task holds ``CHUNK`` tokens, or one longer text.

Defined results: null and empty texts hold the end alone; without training documents N and V are 0, the base is the
formula's value and every word is an unseen one; rows that repeat an id are scored each; a null id is neither held
out nor learnt from; columns other than id and text are ignored; texts are scored whole, the state carried along.
"""

from __future__ import annotations

import bisect
import copy
import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset.llm import gru
from vpcoreset.llm.common import stored, trimmed

END = b"\n"
HEAD, TAIL_CLASSES, CHUNK, LONGEST = 2048, 32, 1_000_000, 64
#: A task hands on its counts when it holds so many words.
COUNTED = 300_000


def tokens(text: str | None) -> list[bytes]:
    """bytes.lower and bytes.split treat ASCII alone: A-Z, and exactly space, tab, LF, VT, FF and CR."""
    return [*text.encode("utf-8", "surrogatepass").lower().split(), END] if text else [END]


def _count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    tally: Counter = Counter()
    for batch in batches:
        for text in batch["text"]:
            tally.update(tokens(text))
            if len(tally) > COUNTED:
                yield pd.DataFrame({"word": list(tally.keys()), "c": list(tally.values())})
                tally = Counter()
    if tally:
        yield pd.DataFrame({"word": list(tally.keys()), "c": list(tally.values())})


def _prefix(word: bytes) -> int:
    return int.from_bytes(word[:3].ljust(3, b"\0"), "big")


class Vocabulary:
    """Counts and codes; code 0 is the start, then the head, then one code for each tail class."""

    def __init__(self, head: list[tuple[bytes, int]], bounds: list[int], held: dict[bytes, int], n: int, v: int, tail: dict[int, tuple[int, int]], discount: float):
        self.head, self.bounds, self.n, self.v, self.discount = head, bounds, n, v, discount
        self.head_classes = -(-len(head) // gru.IN_CLASS)
        k = len(bounds) + 1
        mass = np.array([tail.get(i, (0, 0))[0] for i in range(k)], float)
        words = np.array([tail.get(i, (0, 0))[1] for i in range(k)], float)
        self.tail_mass = mass
        #: log10 probability, inside a tail class, of any unseen word.
        self.unseen = np.log10(np.where(mass > 0, np.maximum(discount * words, 1e-3) / np.maximum(mass, 1), 1.0))
        self.codes = gru.Codes(
            np.concatenate([[0], np.arange(len(head)) // gru.IN_CLASS, self.head_classes + np.arange(k)]),
            np.concatenate([[-1], np.arange(len(head)) % gru.IN_CLASS, np.full(k, -1)]))

        # Tables with a row for each word of the head, each held word, and each tail class.
        self.words = [w for w, _ in head] + list(held)
        count = np.array([c for _, c in head] + list(held.values()), float)
        cls = np.searchsorted(bounds, np.fromiter(map(_prefix, held), np.int64, len(held)), "right") if held else np.zeros(0, np.int64)
        self.code = np.concatenate([1 + np.arange(len(head)), 1 + len(head) + cls, 1 + len(head) + np.arange(k)]).astype(np.int32)
        self.base = np.concatenate([np.log10((count + 0.1) / (n + 0.1 * (v + 1))), np.zeros(k)])
        inner = np.log10((count[len(head) :] - discount) / mass[cls]) if held else np.zeros(0)
        self.inner = np.concatenate([np.zeros(len(head)), inner, np.zeros(k)])

    def bare(self) -> Vocabulary:
        """What training and scoring take: no rows of words."""
        out = copy.copy(self)
        out.words, out.code, out.base, out.inner = [], None, None, None
        return out

    def tail_class(self, word: bytes) -> int:
        return bisect.bisect_right(self.bounds, _prefix(word))

    def parameters(self) -> dict[str, np.ndarray]:
        words = np.zeros((self.head_classes, gru.IN_CLASS))
        words.ravel()[: len(self.head)] = [c for _, c in self.head]
        return gru.initial(len(self.codes.cls), np.concatenate([words.sum(1), np.maximum(self.tail_mass, 0.1)]), words)


class Reader(dict):
    """Raw word -> row of the vocabulary's tables; all words of a class whose counts are not held share a row."""

    def __init__(self, vocabulary: Vocabulary):
        super().__init__(zip(vocabulary.words, range(len(vocabulary.words)), strict=True))
        self.v, self.room = vocabulary, 1 << 18

    def __missing__(self, word: bytes) -> int:
        row = len(self.v.words) + self.v.tail_class(word)
        if self.room:
            self.room -= 1
            self[word] = row
        return row

    def __call__(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words))


def build_vocabulary(counts: DataFrame, held: int) -> Vocabulary:
    """From (word, c) of all training tokens."""
    size = counts.agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("v"), F.sum((F.col("c") == 1).cast("long")).alias("n1"), F.sum((F.col("c") == 2).cast("long")).alias("n2")).collect()[0]
    n, v = size["n"] or 0, size["v"]
    discount = (size["n1"] or 0) / max((size["n1"] or 0) + 2 * (size["n2"] or 0), 1)
    discount = min(max(discount, 0.1), 0.9)
    top = counts.where(F.length("word") <= LONGEST).orderBy(F.desc("c"), "word").limit(HEAD).collect()
    head = [(bytes(r["word"]), r["c"]) for r in top]
    if not any(w == END for w, _ in head):
        head = [*head[: HEAD - 1], (END, counts.where(F.col("word") == END).agg(F.coalesce(F.sum("c"), F.lit(0))).collect()[0][0])]
    # A row for each count below 10,000; the least count that at most ``held`` words have or exceed.
    steps = counts.groupBy(F.least("c", F.lit(10_000)).alias("c")).agg(F.count(F.lit(1)).alias("n")).collect()
    least, total = 10_001, 0
    for r in sorted(steps, key=lambda r: -r["c"]):
        total += r["n"]
        if total > held:
            break
        least = r["c"]
    kept = counts.where((F.col("c") >= least) & (F.length("word") <= LONGEST)).select("word", "c").toArrow()
    names = {w for w, _ in head}
    known = {w: c for w, c in zip(kept.column("word").to_pylist(), kept.column("c").to_pylist(), strict=True) if w not in names}
    del kept
    # Ranges of spelling: cut points among the heaviest three-byte prefixes, about equal in mass.
    code = F.conv(F.rpad(F.hex(F.substring("word", 1, 3)), 6, "0"), 16, 10).cast("long")
    prefixed = counts.join(F.broadcast(counts.sparkSession.createDataFrame([(bytearray(w),) for w in sorted(names)], "word binary")), "word", "left_anti").select(code.alias("prefix"), "c")
    heavy = sorted((r["prefix"], r["c"]) for r in prefixed.groupBy("prefix").agg(F.sum("c").alias("c")).orderBy(F.desc("c"), "prefix").limit(4096).collect())
    bounds: list[int] = []
    part, mass = sum(c for _, c in heavy) / TAIL_CLASSES, 0.0
    for prefix, c in heavy:
        if mass >= part * (len(bounds) + 1) and len(bounds) < TAIL_CLASSES - 1:
            bounds.append(prefix)
        mass += c
    cls = F.lit(0)
    for b in bounds:
        cls = cls + (F.col("prefix") >= b).cast("int")
    tail = {r["k"]: (r["m"], r["w"]) for r in prefixed.groupBy(cls.alias("k")).agg(F.sum("c").alias("m"), F.count(F.lit(1)).alias("w")).collect()}
    return Vocabulary(head, bounds, known, n, v, tail, discount)


CODED = "row long, id string, n_tokens long, n_known long, base double, inner double, rest binary, codes binary"
CODE = np.dtype("<u2")
#: Tokens of a batch of coded texts.
BATCH_TOKENS = 250_000


def _encode(held):
    def encode(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        v = held.value
        read, known = Reader(v), len(v.words)
        code = v.code.astype(CODE)
        # Keys of rows: the number of the task, then a counter; a repeated task gives the same ones.
        at = TaskContext.get().partitionId() << 36
        mark = [bytes([48 + k]) for k in range(TAIL_CLASSES)]  # a letter before each rare word names its class
        wait: list[tuple] = []
        size = 0

        def answer() -> pd.DataFrame:
            return pd.DataFrame([(at + i, *w) for i, w in enumerate(wait)], columns=["row", "id", "n_tokens", "n_known", "base", "inner", "rest", "codes"])

        for batch in batches:
            for doc, text in zip(batch["id"], batch["text"], strict=True):
                words = tokens(text)
                rows = read(words)
                lost = np.flatnonzero(rows >= known).tolist()
                rest = b" ".join([mark[r - known] + words[i] for i, r in zip(lost, rows[lost].tolist(), strict=True)])
                wait.append((doc, len(words), len(words) - len(lost), float(v.base[rows].sum()), float(v.inner[rows].sum()), rest, code[rows].tobytes()))
                size += len(words)
                if size > BATCH_TOKENS:
                    yield answer()
                    at += len(wait)
                    wait, size = [], 0
        if wait:
            yield answer()

    return encode


def _train(held, rate: float):
    def train(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        vocabulary, params = held.value
        trainer = gru.Trainer({k: p.copy() for k, p in params.items()}, vocabulary.codes, rate)
        texts, size = [], 0
        for batch in batches:
            for raw in batch["codes"]:
                texts.append(np.frombuffer(raw, CODE))
                size += len(texts[-1])
                if size > CHUNK:
                    trainer.fit(texts)
                    texts, size = [], 0
        if texts:
            trainer.fit(texts)
        if trainer.tokens:
            yield pd.DataFrame({"tokens": [trainer.tokens], "loss": [trainer.loss], "params": [gru.pack(trainer.params)]})

    return train


def _average(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    total, size, loss = None, 0, 0.0
    for batch in batches:
        for r in batch.itertuples(index=False):
            value = np.frombuffer(r.params, np.float32).astype(np.float64) * r.tokens
            total, size, loss = value if total is None else total + value, size + r.tokens, loss + r.loss
    if total is not None:
        yield pd.DataFrame({"tokens": [size], "loss": [loss], "params": [(total / size).astype(np.float32).tobytes()]})


def train(rows: DataFrame, vocabulary: Vocabulary, *, rounds: int = 2, rate: float = 0.3) -> dict[str, np.ndarray]:
    """Parameters after the rounds; rows: (id, codes) of training documents."""
    params = vocabulary.parameters()
    schema = "tokens long, loss double, params binary"
    for r in range(rounds):
        held = rows.sparkSession.sparkContext.broadcast((vocabulary.bare(), params))
        part = rows.where(F.pmod(F.xxhash64("id", F.lit(97)), F.lit(rounds)) == r)
        trained = stored(part.select("codes").mapInPandas(trimmed(_train(held, rate)), schema), "replicas")
        n = trained.count()
        while n > 1:
            n = -(-n // 16)
            trained = trained.repartition(n).mapInPandas(_average, schema)
        found = trained.collect()
        if found:
            params = gru.unpack(found[0]["params"], params)
    return params


SCORED = "row long, id string, n_tokens long, n_known long, base double, score double"


def _score(held):
    def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        vocabulary, params = held.value
        wait: list[tuple] = []
        size = 0

        def answer() -> pd.DataFrame:
            frame = pd.DataFrame([w[:-1] for w in wait], columns=["row", "id", "n_tokens", "n_known", "base", "score"])
            frame["score"] += gru.log_likelihood(params, vocabulary.codes, [w[-1] for w in wait]) / math.log(10)
            return frame

        for batch in batches:
            for *values, raw in batch.itertuples(index=False, name=None):
                wait.append((*values, np.frombuffer(raw, CODE)))
                size += len(wait[-1][-1])
                if size > CHUNK:
                    yield answer()
                    wait, size = [], 0
        if wait:
            yield answer()

    return score


def score_documents(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", held: int = 400_000, rounds: int = 2) -> DataFrame:
    """(id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row."""
    rows = docs.select(F.col(id_col).cast("string").alias("id"), F.col(text_col).alias("text"))
    out = F.pmod(F.crc32("id"), F.lit(10)) == 0
    learn = rows.where(~out)
    counts = learn.select("text").mapInPandas(trimmed(_count), "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))
    counts = stored(counts, "word-counts")
    vocabulary = build_vocabulary(counts, held)
    words_held = rows.sparkSession.sparkContext.broadcast(vocabulary)
    coded = stored(rows.mapInPandas(trimmed(_encode(words_held)), CODED), "lm-coded")
    params = train(coded.where(~out), vocabulary, rounds=rounds)
    sent = rows.sparkSession.sparkContext.broadcast((vocabulary.bare(), params))
    scored = stored(coded.drop("rest").mapInPandas(trimmed(_score(sent)), SCORED), "lm-scored")

    each = lambda values, k: F.element_at(F.array(*[F.lit(float(x)) for x in values]), k + 1)
    words = F.split(F.col("rest").cast("string"), " ")
    met = coded.where(F.length("rest") > 0).select("row", F.explode(words).alias("marked"))
    met = met.select("row", (F.ascii("marked") - 48).alias("cls"), F.substring("marked", 2, 1 << 30).cast("binary").alias("word")).join(counts, "word", "left")
    c = F.coalesce(F.col("c"), F.lit(0))
    base = F.log10((c + 0.1) / F.lit(vocabulary.n + 0.1 * (vocabulary.v + 1)))
    inner = F.when(c > 0, F.log10((c - vocabulary.discount) / each(np.maximum(vocabulary.tail_mass, 1), F.col("cls")))).otherwise(each(vocabulary.unseen, F.col("cls")))
    more = met.groupBy("row").agg(F.sum((c > 0).cast("long")).alias("k"), F.sum(base).alias("b"), F.sum(inner).alias("s"))
    zero = F.lit(0)
    return scored.join(more, "row", "left").select(
        F.col("id").cast(docs.schema[id_col].dataType).alias(id_col), F.coalesce(out, F.lit(False)).alias("held_out"), "n_tokens", (F.col("n_known") + F.coalesce("k", zero)).alias("n_known"),
        F.lit(int(vocabulary.n)).cast("long").alias("train_tokens"), (F.col("base") + F.coalesce("b", F.lit(0.0))).alias("base_score"), (F.col("score") + F.coalesce("s", F.lit(0.0))).alias("score"))
