"""Three-round importance sampling over local scores, with exact integer arithmetic and no global sort.

Scores are rounded to quanta of 2**-p, which are written once, with a place: 52 bits of a hash of the id. Each draw picks a
party by its total and a row by its quanta, along the rows in the order of (place, id), so a sample depends on the
seed and the scores alone, not on the number of buckets, on retries, partitions or files.

The order is never built as a whole. Buckets are ranges of places, and a draw goes down through them: prefix sums of the first
level (at most 2**FIRST numbers a party) on the server, then sums of sub-ranges of the buckets that a draw has hit, until a range
holds about LEAF rows, and there the rows. Rows are stored with their running sum inside their bucket, and up to BROADCAST_IDS draws go out to them: one
scan, in which a row finds its draws by binary search. More draws are merged with running sums, on every level below the first, by one window
over (party, range). So a draw costs its place in a sorted range and never meets the other rows one by one. The
quanta are clustered by bucket in directories: buckets without a draw are not read.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field
from itertools import accumulate
from math import ceil, log2

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpcoreset.functions.rng import BITS, place_of, u52_py
from vpcoreset.ledger import CommLedger, construction
from vpcoreset.parties import VerticalDataset
from vpcoreset.sources.io import materialize, shared_path

QUANTA = 40
#: Bits of the cells of a bucket's running sums, in which draws look for their rows.
CELLS = 12
#: Rows of a range in which rows are looked up, and bits that the first and each further level of ranges adds.
LEAF, FIRST, NEXT = 1 << 16, 14, 12
#: Ids of a sample are broadcast up to this number; beyond, they are joined by shuffle.
BROADCAST_IDS = 1_000_000


@dataclass(frozen=True)
class Coreset:
    """Weighted ids. df: replicate, id, draws, weight, where weight counts all draws of the id."""

    df: DataFrame
    m: int
    grand_total: int
    ledger: CommLedger = field(default_factory=CommLedger)

    def materialize(self, ds: VerticalDataset) -> DataFrame:
        """The rows of the sample with all features, joined party by party; charged by the solver that asks for them."""
        ids = self.df.select("id").distinct()
        ids = F.broadcast(ids) if self.m <= BROADCAST_IDS else ids
        return self.df.join(ds.concat(ids), "id")


def quantize(scores: DataFrame, p: int = QUANTA) -> DataFrame:
    """(id, party, place, q): scores in quanta, at least one. Negative or odd scores are refused."""
    s = F.col("score")
    bad = s.isNull() | F.isnan(s) | (s < 0)
    q = F.when(bad, F.raise_error(F.lit("a score is null, not a number or negative")).cast("long")).otherwise(F.greatest(F.lit(1), F.round(s * F.lit(float(1 << p))).cast("long")))
    return scores.select("id", "party", place_of(F.col("id")).alias("place"), q.alias("q"))


def range_of(bits: int):
    """Number of the range that a place falls into, ranges being cut by its first bits."""
    return F.shiftright("place", BITS - bits)


@dataclass(frozen=True)
class Quanta:
    """Stored quanta. df: id, party, place, q, bucket, upto (the running sum of q in (party, bucket)); totals: party -> sums by bucket; bits: of the first level, and of the last."""

    df: DataFrame
    totals: dict[int, list[int]]
    first: int
    last: int

    @property
    def party_totals(self) -> dict[int, int]:
        return {j: sum(b) for j, b in self.totals.items()}

    @property
    def grand(self) -> int:
        return sum(self.party_totals.values())

    def of_buckets(self, buckets: set[int]) -> DataFrame:
        """The rows of some buckets; the others' directories are not read."""
        return self.df if len(buckets) >= 1 << self.first else self.df.where(F.col("bucket").isin(sorted(buckets)))


def store_quanta(scores: DataFrame, p: int = QUANTA, leaf: int = LEAF, rows: int | None = None) -> Quanta:
    """Writes the quanta, clustered by bucket, and takes round 1's sums: parties times buckets numbers reach the server.

    ``rows``: the number of scores, where it is known; else they are written first to be counted.
    """
    df = quantize(scores, p)
    if rows is None or rows <= leaf:
        df = materialize(df, "quanta")
        rows = df.count()
    last = max(0, ceil(log2(max(rows, 1) / leaf)))
    first = min(last, FIRST)
    run = F.sum("q").over(W.partitionBy("bucket", "party").orderBy("place", "id").rowsBetween(W.unboundedPreceding, 0))
    df = df.withColumn("bucket", range_of(first).cast("int"))
    if first:
        path = shared_path(df.sparkSession, "quanta-by-bucket")
        # The window sorts by four columns, of which rows of a bucket share the first two; in the order of one number, nearly all its comparisons are done.
        rest = BITS - first
        near = F.shiftleft(F.col("bucket").cast("long"), 63 - first).bitwiseOR(F.shiftleft(F.col("party").cast("long"), rest)).bitwiseOR(F.col("place").bitwiseAND((1 << rest) - 1))
        df = df.repartition("bucket").sortWithinPartitions(near, "id").withColumn("upto", run)
        df.write.partitionBy("bucket").parquet(path)
        df = df.sparkSession.read.schema(df.schema).parquet(path)
    else:
        df = df.withColumn("upto", run)
    # Two halves of a sum of longs, so that no sum overflows.
    low = F.col("q").bitwiseAND((1 << 31) - 1)
    sums = df.groupBy("party", "bucket").agg(F.sum(F.shiftright("q", 31)).alias("high"), F.sum(low).alias("low")).collect()
    totals: dict[int, list[int]] = {}
    for r in sums:
        totals.setdefault(r["party"], [0] * (1 << first))[r["bucket"]] = (r["high"] << 31) + r["low"]
    if sum(map(sum, totals.values())) >= 1 << 61:
        raise ValueError("scores add up to more than the quanta can count; take fewer bits p")
    return Quanta(df, dict(sorted(totals.items())), first, last)


def allocate_draws(totals: dict[int, int], m: int, seed: str, replicate: int = 0) -> list[int]:
    """Round 1, down: the party of each draw, by its share of the grand total."""
    if m < 1:
        raise ValueError("m must be positive")
    parties, upto = list(totals), list(accumulate(totals.values()))
    return [parties[bisect.bisect_right(upto, (u52_py(seed, "party", replicate, r) * upto[-1]) >> BITS)] for r in range(m)]


def make_thresholds(totals: dict[int, list[int]], m: int, seed: str, replicates: Sequence[int]) -> list[tuple[int, int, int, int, int]]:
    """(replicate, draw_no, party, bucket, threshold inside the bucket) of every draw."""
    upto = {j: list(accumulate(b)) for j, b in totals.items()}
    out = []
    for rep in replicates:
        for r, party in enumerate(allocate_draws({j: u[-1] for j, u in upto.items()}, m, seed, rep)):
            t = (u52_py(seed, "row", rep, r) * upto[party][-1]) >> BITS
            b = bisect.bisect_right(upto[party], t)
            out.append((rep, r, party, b, t - (upto[party][b - 1] if b else 0)))
    return out


def _merge(items: DataFrame, draws: DataFrame, order: Sequence[str]) -> DataFrame:
    """Each draw with the first item, in order inside its (party, range), whose running sum passes its threshold t.

    items: party, range, q and other columns; draws: replicate, draw_no, party, range, t. Draws and running sums are laid
    side by side, in falling order, and a draw takes the item last seen: no pair of a draw and an item is formed.
    """
    run = F.sum("q").over(W.partitionBy("party", "range").orderBy(*order).rowsBetween(W.unboundedPreceding, 0))
    item = F.struct(*[c for c in items.columns if c not in ("party", "range")], run.alias("upto"))
    at = items.select("party", "range", item.alias("item")).select("party", "range", F.col("item.upto").alias("at"), F.lit(0).alias("kind"), "item", F.lit(None).cast("int").alias("replicate"), F.lit(None).cast("int").alias("draw_no"))
    asked = draws.select("party", "range", F.col("t").alias("at"), F.lit(1).alias("kind"), F.lit(None).cast(at.schema["item"].dataType).alias("item"), "replicate", "draw_no")
    seen = F.last("item", ignorenulls=True).over(W.partitionBy("party", "range").orderBy(F.desc("at"), F.desc("kind")).rowsBetween(W.unboundedPreceding, 0))
    return at.unionByName(asked).withColumn("item", seen).where("kind = 1").drop("kind")


def _look_up(quanta: Quanta, thresholds: list[tuple[int, int, int, int, int]]) -> DataFrame:
    """Each draw with its row, which is the one whose running sum first passes the threshold, in one scan; the thresholds go out to all tasks."""
    rows, asked = quanta.of_buckets({t[3] for t in thresholds}).select("party", "bucket", "q", "upto", "id"), {}
    for rep, r, party, bucket, t in thresholds:
        asked.setdefault((party, bucket), []).append((t, rep, r))
    # Running sums are cut into CELLS at least; a row that lies in a cell without a threshold has no draw and isn't looked up.
    cut = max(0, max((max(b) for b in quanta.totals.values()), default=0).bit_length() - CELLS)
    hit = sorted({(party, bucket, t >> cut) for _, _, party, bucket, t in thresholds})
    cells = rows.sparkSession.createDataFrame(pa.table({n: pa.array([h[i] for h in hit], t) for i, (n, t) in enumerate((("party", pa.int32()), ("bucket", pa.int32()), ("cell", pa.int64())))})).withColumn("hit", F.lit(True))
    low, high = F.shiftright(F.col("upto") - F.col("q"), cut), F.shiftright(F.col("upto") - 1, cut)
    rows = rows.withColumn("cell", high).join(F.broadcast(cells), ["party", "bucket", "cell"], "left").where(F.col("hit") | (low < F.col("cell"))).drop("cell", "hit")
    sent = rows.sparkSession.sparkContext.broadcast({at: np.array(sorted(own), np.int64).T for at, own in asked.items()})

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            party, bucket, q, upto = (batch.column(c).to_numpy() for c in ("party", "bucket", "q", "upto"))
            code = party.astype(np.int64) << 32 | bucket
            for one in np.unique(code).tolist():
                if (own := sent.value.get((one >> 32, one & 0xFFFFFFFF))) is None:
                    continue
                at = np.flatnonzero(code == one)
                low, high = np.searchsorted(own[0], upto[at] - q[at]), np.searchsorted(own[0], upto[at])
                times = high - low
                if not times.any():
                    continue
                row = np.repeat(at, times)
                draw = np.repeat(low - np.cumsum(times) + times, times) + np.arange(len(row))
                yield pa.RecordBatch.from_arrays([
                    pa.array(own[1, draw], pa.int32()), pa.array(own[2, draw], pa.int32()), batch.column("party").take(pa.array(row)), batch.column("id").take(pa.array(row)),
                    batch.column("bucket").take(pa.array(row))], ["replicate", "draw_no", "party", "id", "bucket"])

    kind = rows.schema["id"].dataType.simpleString()
    out = materialize(rows.mapInArrow(found, f"replicate int, draw_no int, party int, id {kind}, bucket int"), "draws")
    sent.destroy()
    return out


def draw_rows(quanta: Quanta, thresholds: list[tuple[int, int, int, int, int]]) -> DataFrame:
    """Round 2: (replicate, draw_no, party, id, bucket)."""
    if len(thresholds) <= BROADCAST_IDS:
        return _look_up(quanta, thresholds)
    spark = quanta.df.sparkSession
    columns = list(zip(*thresholds, strict=True)) if thresholds else [[]] * 5
    draws = spark.createDataFrame(pa.table({
        n: pa.array(c, t) for n, c, t in zip(("replicate", "draw_no", "party", "range", "t"), columns, (pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int64()), strict=True)}))
    rows = quanta.of_buckets({t[3] for t in thresholds})
    bits = quanta.first

    def hit() -> DataFrame:
        return rows.withColumn("range", range_of(bits)).join(draws.select("party", "range").distinct(), ["party", "range"], "left_semi")

    while bits < quanta.last:
        deeper = min(bits + NEXT, quanta.last)
        sums = hit().groupBy("party", "range", range_of(deeper).alias("sub")).agg(F.sum("q").alias("q"))
        found = _merge(sums, draws, ["sub"])
        draws = materialize(found.select("replicate", "draw_no", "party", F.col("item.sub").alias("range"), (F.col("at") - F.col("item.upto") + F.col("item.q")).alias("t")), "draws")
        bits = deeper
    found = _merge(hit().select("party", "range", "q", "place", "id", "bucket"), draws, ["place", "id"])
    return materialize(found.select("replicate", "draw_no", "party", F.col("item.id").alias("id"), F.col("item.bucket").alias("bucket")), "draws")


def gather_scores(draws: DataFrame, quanta: Quanta, thresholds: list[tuple[int, int, int, int, int]]) -> DataFrame:
    """Round 3, up: (id, q) with the quanta of all parties added; a row's quanta of all parties lie in one bucket."""
    ids = draws.select("id").distinct()
    ids = F.broadcast(ids) if len(thresholds) <= BROADCAST_IDS else ids
    return quanta.of_buckets({t[3] for t in thresholds}).join(ids, "id", "left_semi").groupBy("id").agg(F.sum("q").alias("q"))


def weigh(draws: DataFrame, gathered: DataFrame, grand_total: int, m: int, collapse: bool = True) -> DataFrame:
    """Round 3: weight of a draw is grand total / (m * quanta of its row); collapsed rows add up their draws."""
    if collapse:
        draws = draws.groupBy("replicate", "id").agg(F.count(F.lit(1)).alias("draws"))
    else:
        draws = draws.withColumn("draws", F.lit(1).cast("long"))
    return draws.join(gathered, "id").withColumn("weight", F.col("draws") * F.lit(float(grand_total)) / (F.lit(float(m)) * F.col("q"))).drop("q")


def two_level_sample(scores: DataFrame, m: int, seed: str = "sample", *, replicates: Sequence[int] = (0,), leaf: int = LEAF, p: int = QUANTA, policy: str = "strict", collapse: bool = True, masked: bool = False) -> Coreset:
    """m draws with replacement for each replicate from (id, party, score).

    With ``masked`` the server gets the sums of round 3 by masked addition and no party's own score.
    """
    if m < 1:
        raise ValueError("m must be positive")
    quanta = store_quanta(scores, p, leaf)
    if not quanta.totals:
        raise ValueError("no rows to draw from")
    thresholds = make_thresholds(quanta.totals, m, seed, replicates)
    draws = draw_rows(quanta, thresholds)
    counts = [sum(1 for t in thresholds if t[2] == j and t[0] == replicates[0]) for j in quanta.totals]
    if masked:
        from vpcoreset.privacy import secure_sum

        own = quanta.of_buckets({t[3] for t in thresholds}).join(draws.select("id").distinct(), "id", "left_semi")
        gathered = secure_sum(own.select("id", "party", "q"), seed)
    else:
        gathered = gather_scores(draws, quanta, thresholds)
    weighted = weigh(draws, gathered, quanta.grand, m, collapse)
    cols = ["replicate", "id", "draws", "weight"] if collapse else ["replicate", "draw_no", "party", "id", "draws", "weight"]
    return Coreset(weighted.select(*cols), m, quanta.grand, construction(m, counts, "coreset", policy, masked))


def sample_grid(scores: DataFrame, sizes: Sequence[int], replicates: int, seed: str = "grid", *, leaf: int = LEAF, p: int = QUANTA, rows: int | None = None) -> DataFrame:
    """(size, replicate, id, draws, weight) for all sizes and replicates in one pass: a sample of m is the first m draws. ``rows``: the number of scores, where it is known."""
    quanta = store_quanta(scores, p, leaf, rows)
    thresholds = make_thresholds(quanta.totals, max(sizes), seed, range(replicates))
    draws = draw_rows(quanta, thresholds)
    grand = float(quanta.grand)
    sized = draws.withColumn("size", F.explode(F.array(*[F.lit(s) for s in sizes]))).where(F.col("draw_no") < F.col("size"))
    sized = sized.groupBy("size", "replicate", "id").agg(F.count(F.lit(1)).alias("draws"))
    gathered = gather_scores(draws, quanta, thresholds)
    return sized.join(gathered, "id").withColumn("weight", F.col("draws") * F.lit(grand) / (F.col("size") * F.col("q"))).drop("q")


def uniform_scores(ds: VerticalDataset) -> DataFrame:
    """Equal scores at one party: the sampler then draws rows uniformly, with weight n / m."""
    return ds.parties[0].df.select("id", F.lit(0).alias("party"), F.lit(2.0**-20).alias("score"))


def uniform_sample(ds: VerticalDataset, m: int, seed: str = "uniform", **more) -> Coreset:
    """m uniform draws with replacement; weights are known to the server and are not sent."""
    out = two_level_sample(uniform_scores(ds), m, seed, p=20, **more)
    return Coreset(out.df, m, out.grand_total, construction(m, [m] * len(ds.parties), "uniform"))


def bernoulli_sample(df: DataFrame, share: float, seed: str = "bernoulli") -> DataFrame:
    """Each row by itself with this probability, by a hash of the id; weight 1 / share."""
    from vpcoreset.functions.rng import u52

    return df.where(u52(seed, F.col("id")) < int(share * (1 << BITS))).withColumn("weight", F.lit(1.0 / share))


def smallest_hashes(df: DataFrame, m: int, seed: str = "without") -> DataFrame:
    """m distinct rows, uniformly, by their smallest hashes (a top-k heap a task)."""
    from vpcoreset.functions.rng import u52

    return df.withColumn("u", u52(seed, F.col("id"))).orderBy("u", "id").limit(m).drop("u")
