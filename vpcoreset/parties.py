"""Parties, vertical datasets, column splitters and local standardisation.

A party is one DataFrame that holds its own columns under a shared key; the blocks are never joined for scoring.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import NumericType

from vpcoreset.functions.rng import u52
from vpcoreset.sources.fixtures import FIXTURES, read
from vpcoreset.sources.io import materialize


@dataclass(frozen=True)
class PartySpec:
    """A column block: ``df`` holds ``id``, the features, and where given a label and a weight, all numeric."""

    name: str
    df: DataFrame
    features: tuple[str, ...]
    label: str | None = None
    weight: str | None = None
    #: The frame whose block is in the shared folder, or a projection of one; another ``df`` is not stored.
    stored: DataFrame | None = field(default=None, compare=False, repr=False)

    def __post_init__(self):
        types = {f.name: f.dataType for f in self.df.schema.fields}
        wanted = [*self.features, *[c for c in (self.label, self.weight) if c]]
        if missing := [c for c in ("id", *wanted) if c not in types]:
            raise ValueError(f"party {self.name} lacks {missing}")
        if odd := [c for c in wanted if not isinstance(types[c], NumericType)]:
            raise ValueError(f"party {self.name}: {odd} are not numeric")
        if len(set(wanted)) < len(wanted):
            raise ValueError(f"party {self.name} names a column twice")

    @property
    def columns(self) -> list[str]:
        """The matrix of the party: its features, and the label at the party that has it."""
        return [*self.features, *([self.label] if self.label else [])]

    def block(self) -> DataFrame:
        cols = [*self.columns, *([self.weight] if self.weight else [])]
        return self.df.select("id", *[F.col(c).cast("double").alias(c) for c in cols])


@dataclass(frozen=True)
class VerticalDataset:
    parties: tuple[PartySpec, ...]

    def __post_init__(self):
        if not self.parties:
            raise ValueError("no party")
        if len([p for p in self.parties if p.label]) > 1 or any(p.label for p in self.parties[:-1]):
            raise ValueError("the label belongs to the last party alone")
        names = [c for p in self.parties for c in p.columns]
        if len(set(names)) < len(names):
            raise ValueError("two parties share a column name")

    @property
    def features(self) -> list[str]:
        return [c for p in self.parties for c in p.features]

    @property
    def label(self) -> str | None:
        return self.parties[-1].label

    def map(self, change) -> VerticalDataset:
        return VerticalDataset(tuple(change(p) for p in self.parties))

    def align(self, how: str = "strict") -> VerticalDataset:
        """'strict' fails unless all parties hold the same ids; 'inner' keeps the common ones."""
        if how == "strict":
            for other in self.parties[1:]:
                gaps = self.parties[0].df.select("id").join(other.df.select(F.col("id").alias("id2")), F.col("id") == F.col("id2"), "full")
                if gaps.where(F.col("id").isNull() | F.col("id2").isNull()).limit(1).count():
                    raise ValueError(f"ids of {self.parties[0].name} and {other.name} differ")
            return self
        common = self.parties[0].df.select("id")
        for other in self.parties[1:]:
            common = common.join(other.df.select("id"), "id", "left_semi")
        return self.restrict(common)

    def restrict(self, ids: DataFrame) -> VerticalDataset:
        return self.map(lambda p: replace(p, df=p.df.join(ids.select("id"), "id", "left_semi")))

    def split(self, test_share: float, seed: str = "split") -> tuple[VerticalDataset, VerticalDataset]:
        """Train and test part by a hash of the id; every party decides alike, without exchange."""
        cut = int(test_share * (1 << 52))
        test = u52(seed, F.col("id")) < cut
        return self.map(lambda p: replace(p, df=p.df.where(~test))), self.map(lambda p: replace(p, df=p.df.where(test)))

    def concat(self, ids: DataFrame | None = None) -> DataFrame:
        """id with all features and the label; for samples (ids) and for baselines that move all columns."""
        out = None
        for p in self.parties:
            block = p.block()
            if ids is not None:
                block = block.join(ids.select("id"), "id", "left_semi")
            out = block if out is None else out.join(block, "id")
        return out


def dataset(spark: SparkSession, sf_dir: str, name: str, *, standard: bool = False, label: bool = True) -> VerticalDataset:
    """A fixture on the given tables."""
    f = FIXTURES[name]
    last = len(f.parties) - 1
    ds = VerticalDataset(tuple(
        PartySpec(f"p{j + 1}", read(spark, sf_dir, sql), names, f.label if label and j == last else None) for j, (names, sql) in enumerate(f.parties)))
    return standardize(ds) if standard else ds


def standardize(ds: VerticalDataset, fit: VerticalDataset | None = None) -> VerticalDataset:
    """Each party scales its own columns to mean 0 and deviation 1 (population) of ``fit``, or of itself; constant columns become 0.

    Without ``fit`` the block is stored first: its columns are derived once for the statistics and for all that follows.
    """

    def scale(p: PartySpec, q: PartySpec) -> PartySpec:
        stats = q.block().agg(*[f(c).alias(f"{k}_{i}") for i, c in enumerate(q.columns) for k, f in (("m", F.avg), ("s", F.stddev_pop))]).collect()[0]
        kept = p.block().select("id", *([p.weight] if p.weight else []), *[standard_score(F.col(c), stats[f"m_{i}"], stats[f"s_{i}"]).alias(c) for i, c in enumerate(p.columns)])
        return replace(p, df=kept, stored=kept if p.stored is p.df else None)

    ds = ds if fit else ds.map(pin)
    return VerticalDataset(tuple(scale(p, q) for p, q in zip(ds.parties, (fit or ds).parties, strict=True)))


def standard_score(x: Column, mean: float | None, deviation: float | None) -> Column:
    return (x - F.lit(mean)) / F.lit(deviation) if deviation else F.lit(0.0)


def split_even(df: DataFrame, features: Sequence[str], parties: int) -> VerticalDataset:
    """Features dealt in order to parties of equal width, the first ones wider by one where it does not divide."""
    base, more = divmod(len(features), parties)
    widths = [base + (j < more) for j in range(parties)]
    cuts = [sum(widths[:j]) for j in range(parties + 1)]
    return split_by_names(df, [list(features[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)])


def split_by_names(df: DataFrame, blocks: Sequence[Sequence[str]], label: str | None = None) -> VerticalDataset:
    last = len(blocks) - 1
    return VerticalDataset(tuple(
        PartySpec(f"p{j + 1}", df.select("id", *b, *([label] if label and j == last else [])), tuple(b), label if j == last else None) for j, b in enumerate(blocks)))


def split_vector(df: DataFrame, vector: str, widths: Sequence[int]) -> VerticalDataset:
    """An array column cut into blocks of named scalar columns."""
    parties, at = [], 0
    for j, w in enumerate(widths):
        names = tuple(f"e{i}" for i in range(at, at + w))
        parties.append(PartySpec(f"p{j + 1}", df.select("id", *[F.element_at(vector, i + 1).cast("double").alias(f"e{i}") for i in range(at, at + w)]), names))
        at += w
    return VerticalDataset(tuple(parties))


def pin(p: PartySpec) -> PartySpec:
    """The party with its block written to the shared folder: passes of an iteration read its numbers, not what they derive from.

    A block that is there already, or was scaled from one, is not written again.
    """
    if p.stored is p.df:
        return p
    df = materialize(p.block(), p.name)
    return replace(p, df=df, stored=df)


def check_numeric(df: DataFrame, cols: Sequence[str]) -> DataFrame:
    """One row: how many values of each column are null, and how many are not finite."""
    bad = lambda c: F.isnan(c) | (F.abs(F.col(c)) == float("inf"))
    return df.agg(*[F.sum(F.col(c).isNull().cast("long")).alias(f"{c}_null") for c in cols], *[F.sum(F.coalesce(bad(c), F.lit(False)).cast("long")).alias(f"{c}_odd") for c in cols])


def handle_nulls(p: PartySpec, on_null: str = "reject") -> PartySpec:
    """'reject' fails, 'drop' drops rows, 'zero' and 'mean' fill."""
    if on_null == "reject":
        row = check_numeric(p.df, p.columns).collect()[0].asDict()
        if any(row.values()):
            raise ValueError(f"party {p.name}: {({k: v for k, v in row.items() if v})}")
        return p
    if on_null == "drop":
        return replace(p, df=p.df.dropna(subset=p.columns))
    if on_null == "zero":
        return replace(p, df=p.df.fillna(0, subset=p.columns))
    if on_null == "mean":
        means = p.df.agg(*[F.avg(c).alias(c) for c in p.columns]).collect()[0].asDict()
        return replace(p, df=p.df.fillna({c: m for c, m in means.items() if m is not None}))
    raise ValueError(on_null)
