"""N-gram Jaccard join with a MinHash LSH forest and exact verification.

A text is the set of its five-word shingles. Texts with equal sets form one class, of which the smallest id goes on.
A signature holds ``trees * depth`` minima of keyed hashes of the set, 16 bits each; a tree is a prefix trie over
``depth`` of them, kept as rows that are sorted by the tree's number and its minima, so that the texts below a trie node lie
side by side. Texts below a shared node are candidates.

The search starts at the deepest nodes and shortens the matched prefix by one in all trees at a time, until the target
recall is reached. What has been found decides: a pair of similarity s meets below a node of depth p in some tree with
probability ``1 - (1 - s**p) ** trees``, so every found pair, by the similarity of its signatures, stands for the inverse of it
in pairs that exist. One unseen pair of just the wanted similarity is counted on top, so a set without any pair is
searched to the depth that suffices in the worst case. A set of close copies ends at deep prefixes, one of borderline
pairs goes on to shorter ones; and after the first step only nodes that hold several of the groups found so far are read.

Inside a node, signatures are compared, and what agrees in clearly fewer places than the similarity would (nine
standard deviations of the estimate) is dropped. Nodes and groups larger than ``block`` are dealt by hash into
blocks, and each pair of blocks is a task of its own: work on large groups spreads out, no pair is listed, and
only spanning trees leave a task. The components of these trees are the groups in which all pairs are
verified exactly on the shingle sets, again by pairs of blocks, each pair once.

Result: a row for each document with the least id of its connected group of links and its number of links,
i.e. of other documents with a similarity of ``threshold`` or more, equal ones included.

Defined results: null and empty texts have no shingle, no link and are groups of their own; a text of fewer than
five words is one shingle; rows that repeat an id count as copies of it; rows without an id link to nothing and have no class; columns other than id and text are ignored;
texts are read whole. Ids are integers.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset.llm.common import groups, hash_texts, mix64, shingles, stored, trimmed
from vpcoreset.llm.graphs import components

TREES, DEPTH = 24, 6
_N = TREES * DEPTH
_XOR = mix64(np.arange(1, _N + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_MUL = mix64(_XOR) | np.uint64(1)
AT_ONCE = 1 << 16


def meeting(similarity: float, p: int) -> float:
    """Probability that two texts of this similarity share a prefix of p minima in some tree."""
    return 1 - (1 - similarity**p) ** TREES


def recall_estimate(tally: dict[int, float], p: int, threshold: float) -> float:
    """Share of the existing pairs that prefixes of p minima have found; tally: found pairs by the places in which signatures agree."""
    near = {a / _N: n for a, n in tally.items() if a / _N >= threshold}
    return (sum(near.values()) + 1) / (sum(n / meeting(s, p) for s, n in near.items()) + 1 / meeting(threshold, p))


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """A row of 16-bit minima for each set; sets must not be empty."""
    out = np.empty((len(sets), _N), np.uint16)
    at = 0
    while at < len(sets):
        end, size = at, 0
        while end < len(sets) and (size == 0 or size + len(sets[end]) <= AT_ONCE):
            size += len(sets[end])
            end += 1
        h = np.concatenate(sets[at:end])
        start = np.concatenate([[0], np.cumsum([len(s) for s in sets[at : end - 1]])]).astype(np.int64)
        for k in range(_N):
            out[at:end, k] = mix64(np.minimum.reduceat((h ^ _XOR[k]) * _MUL[k], start)) >> np.uint64(48)
        at = end
    return out


def _sign(width: int):
    def sign(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            sets = [shingles(words, width) for words in hash_texts(batch["text"])]
            full = [i for i, s in enumerate(sets) if len(s)]
            if not full:
                continue
            sig = signatures([sets[i] for i in full])
            yield pd.DataFrame({
                "id": batch["id"].to_numpy()[full],
                "key": [hashlib.blake2b(sets[i].tobytes(), digest_size=16).digest() for i in full],
                "sig": [row.tobytes() for row in sig],
            })

    return sign


def _roots(n: int, pairs: np.ndarray) -> np.ndarray:
    """Least member of each item's component, items 0..n-1 and rows (a, b)."""
    root = np.arange(n)
    while True:
        new = root.copy()
        np.minimum.at(new, pairs[:, 0], root[pairs[:, 1]])
        np.minimum.at(new, pairs[:, 1], root[pairs[:, 0]])
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _deal(rows: DataFrame, group: str, size: str, block: int) -> DataFrame:
    """Rows with the pairs of blocks (i, j), i <= j, of their group that they take part in, and their own block."""
    rows = rows.withColumn("blocks", F.ceil(F.col(size) / block).cast("int"))
    rows = rows.withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    return rows.withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")}).drop("blocks", "other", size)


def _alike(least: int, p: int):
    """Of the members of a trie node, pairs that were not in one group before and whose signatures agree in at least so many places.

    Rows are either edges (a, b) of spanning trees, or (agree, pairs): a pair counts one over the number of trees in which it meets.
    """

    def alike(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        a, b, tally = [], [], np.zeros(_N + 1)
        for g in groups(batches, ["node", "i", "j"]):
            if len(g) > 1:
                ids, own, label = g["id"].to_numpy(), g["own"].to_numpy(), g["label"].to_numpy()
                sig = np.frombuffer(b"".join(g["sig"]), np.uint16).reshape(len(g), _N)
                cross = g["i"].iloc[0] != g["j"].iloc[0]
                pairs = []
                for k in range(len(g) - 1):
                    same = sig[k + 1 :] == sig[k]
                    agree = same.sum(1)
                    ok = (agree >= least) & (label[k + 1 :] != label[k])
                    if cross:
                        ok &= own[k + 1 :] != own[k]
                    hit = np.flatnonzero(ok)
                    if len(hit):
                        met = same[hit].reshape(len(hit), TREES, DEPTH)[:, :, :p].all(2).sum(1)
                        np.add.at(tally, agree[hit], 1 / met)
                        pairs.append(np.stack([np.full(len(hit), k), hit + k + 1], 1))
                if pairs:
                    root = _roots(len(g), np.concatenate(pairs))
                    new = np.flatnonzero(root != np.arange(len(g)))
                    a += ids[new].tolist()
                    b += ids[root[new]].tolist()
            if len(a) > 10_000:
                yield pd.DataFrame({"a": a, "b": b, "agree": -1, "pairs": 0.0})
                a, b = [], []
        yield pd.DataFrame({"a": np.array(a, np.int64), "b": np.array(b, np.int64), "agree": -1, "pairs": 0.0})
        seen = np.flatnonzero(tally)
        yield pd.DataFrame({"a": np.int64(0), "b": np.int64(0), "agree": seen, "pairs": tally[seen]})

    return alike


def forest_groups(classes: DataFrame, threshold: float, recall: float, block: int) -> tuple[DataFrame, int]:
    """(node, label) of the texts that any trie joins, and the depth at which the shortening of prefixes ended; classes: (id, sig)."""
    spread = (threshold * (1 - threshold) / _N) ** 0.5
    least = int(_N * (threshold - 9 * spread))
    rows = classes.select("id", "sig", F.col("id").alias("label"))
    edges, grouped, tally = None, None, {}
    for p in range(DEPTH, 0, -1):
        slices = F.array(*[F.concat(F.lit(bytes([t])), F.substring("sig", t * DEPTH * 2 + 1, p * 2)) for t in range(TREES)])
        nodes = rows.select("id", "label", F.explode(slices).alias("node"))
        open_ = nodes.groupBy("node").agg(F.count(F.lit(1)).alias("members"), F.min("label").alias("least"), F.max("label").alias("most"))
        open_ = open_.where(F.col("least") != F.col("most")).select("node", "members")
        inside = _deal(nodes.join(open_, "node").join(classes.select("id", "sig"), "id"), "node", "members", 2 * block)
        inside = inside.repartition("node", "i", "j").sortWithinPartitions("node", "i", "j", "id")
        found = stored(inside.select("node", "i", "j", "own", "id", "label", "sig").mapInPandas(trimmed(_alike(least, p)), "a long, b long, agree int, pairs double"), "candidates")
        for r in found.where("agree >= 0").groupBy("agree").agg(F.sum("pairs").alias("pairs")).collect():
            tally[r["agree"]] = tally.get(r["agree"], 0.0) + r["pairs"]
        new = found.where("agree < 0").select("a", "b")
        edges = new if edges is None else edges.unionByName(new)
        grouped = components(edges.distinct())
        if recall_estimate(tally, p, threshold) >= recall:
            break
        rows = stored(classes.select("id", "sig").join(grouped.withColumnRenamed("node", "id"), "id", "left").withColumn("label", F.coalesce("label", "id")), "forest")
    return grouped, p


def common_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all pairwise intersections."""
    n = len(sets)
    if n == 2:
        both = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        return np.array([[len(sets[0]), both], [both, len(sets[1])]])
    value, owner = np.concatenate(sets), np.repeat(np.arange(n), [len(s) for s in sets])
    _, code, count = np.unique(value, return_inverse=True, return_counts=True)
    shared = count[code] > 1
    owner, code = owner[shared], np.unique(code[shared], return_inverse=True)[1]
    order = np.argsort(code, kind="stable")
    owner, code = owner[order], code[order]
    out = np.zeros((n, n), np.float32)
    for low in range(0, int(code[-1]) + 1 if len(code) else 0, 2048):
        a, b = np.searchsorted(code, [low, low + 2048])
        there = np.zeros((n, 2048), np.float32)
        there[owner[a:b], code[a:b] - low] = 1
        out += there @ there.T
    return out


def _verify(width: int, threshold: float):
    """Links of each member of a group, and the least member that its links lead to."""

    def verify(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for g in groups(batches, ["label", "i", "j"]):
            if len(g) < 2:
                continue
            g = g.sort_values("id", ignore_index=True)
            sets = [shingles(words, width) for words in hash_texts(g["text"])]
            size = np.array([len(s) for s in sets], float)
            linked = common_counts(sets) * (1 + threshold) >= threshold * (size[:, None] + size[None, :]) - 1e-6
            np.fill_diagonal(linked, False)
            if g["i"].iloc[0] != g["j"].iloc[0]:
                own = g["own"].to_numpy()
                linked &= own[:, None] != own[None, :]
            ids = g["id"].to_numpy()
            root = _roots(len(g), np.argwhere(linked))
            yield pd.DataFrame({"id": ids, "links": (linked * g["copies"].to_numpy()[None, :]).sum(1), "root": ids[root]})

    return verify


def ngram_join(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 5, threshold: float = 0.8, recall: float = 0.9999, block: int = 512) -> DataFrame:
    """(id, class_id, n_links) of every row."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    signed = stored(rows.where(F.col("id").isNotNull()).mapInPandas(trimmed(_sign(width)), "id long, key binary, sig binary"), "signed")
    classes = signed.groupBy("key").agg(F.min(F.struct("id", "sig")).alias("least"), F.count(F.lit(1)).alias("copies"))
    classes = stored(classes.select("key", "least.id", "least.sig", "copies"), "classes")

    grouped, _ = forest_groups(classes, threshold, recall, block)

    sizes = grouped.groupBy("label").agg(F.count(F.lit(1)).alias("members"))
    member = grouped.join(sizes, "label").join(classes.select(F.col("id").alias("node"), "copies", "key"), "node").withColumnRenamed("node", "id")
    # Rows that repeat an id are told apart by their sets; of equal ones any serves.
    first = rows.join(member.select("id").distinct(), "id", "left_semi").groupBy("id").agg(F.min("text").alias("text"))
    texts = _deal(first.join(member.drop("key"), "id"), "label", "members", block)
    texts = texts.repartition("label", "i", "j").sortWithinPartitions("label", "i", "j", "id")
    found = stored(texts.select("label", "i", "j", "own", "id", "copies", "text").mapInPandas(trimmed(_verify(width, threshold)), "id long, links long, root long"), "links")

    linked = components(found.where("root <> id").select(F.col("id").alias("a"), F.col("root").alias("b")))
    links = found.groupBy("id").agg(F.sum("links").alias("links"))
    per_class = classes.select("key", "id", "copies").join(links, "id", "left").join(linked.withColumnRenamed("node", "id"), "id", "left")
    per_class = per_class.select("key", F.coalesce("label", "id").alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    keyed = signed.select("id", "key").join(per_class, "key").select("id", "class_id", "n_links")
    empty = rows.where(F.col("id").isNull() | (F.regexp_count(F.coalesce("text", F.lit("")), F.lit(r"[^\x20\x09-\x0D]")) == 0)).select("id", F.col("id").alias("class_id"), F.lit(0).cast("long").alias("n_links"))
    return keyed.unionByName(empty).withColumnRenamed("id", id_col)
