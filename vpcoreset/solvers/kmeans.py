"""k-means: seeding and Lloyd steps on the cluster for full blocks, and weighted numpy versions for samples.

Passes over all rows read numpy blocks that are made once (``Held``).
Lloyd on the cluster: tasks add up their rows by cell, and k rows come back. Seeding by squared
distance is a race: the row of the least ``-ln(u) / d2`` is drawn with a probability in proportion to d2, u being a hash of the id. So a
seed costs one aggregate, and a repeat gives the same seeds. Several starts share their jobs: each seed and each step of
all of them is one scan.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterable, Iterator, Sequence
from contextlib import contextmanager
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vpcoreset.functions import vectors
from vpcoreset.functions.rng import BITS, spell, u52_many, u52_spelled
from vpcoreset.parties import PartySpec

#: Rows of a block of costs and cells, models that share a product, and rows whose distances are taken together.
BLOCK, TOGETHER, STRIP = 1024, 16, 4096


def first_centers(p: PartySpec, k: int) -> np.ndarray:
    """The rows of the k least ids."""
    rows = p.block().select("id", *p.features).orderBy("id").limit(k).collect()
    return np.array([[r[c] for c in p.features] for r in rows])


def farthest_centers(p: PartySpec, k: int) -> np.ndarray:
    """The row of the least id, then again and again the row farthest from all chosen; ties to the least id."""
    centers = first_centers(p, 1)
    while len(centers) < k:
        best = vectors.nearest([F.col(c) for c in p.features], centers)
        top = p.block().select("id", *p.features, best["d2"].alias("d2")).orderBy(F.desc("d2"), "id").limit(1).collect()[0]
        centers = np.vstack([centers, [[top[c] for c in p.features]]])
    return centers


def _weight(p: PartySpec):
    return F.col(p.weight).cast("double") if p.weight else F.lit(1.0)


@dataclass(frozen=True)
class Held:
    """Rows of a party as numpy blocks, for the passes of an iteration: derived and moved into arrays once, then kept on the executors' disks.

    A block is (ids, features x rows, weights); ids are integers, or texts where the id is of another kind.
    """

    party: PartySpec
    blocks: RDD

    @property
    def features(self) -> list[str]:
        return list(self.party.features)

    def each(self, work: Callable[[Iterator[tuple]], Iterable]) -> list:
        """What the tasks hand on, in the order of the partitions."""
        return self.blocks.mapPartitions(lambda found: work(map(pickle.loads, found))).collect()

    def release(self) -> None:
        self.blocks.unpersist()


def hold(p: PartySpec) -> Held:
    whole = isinstance(p.df.schema["id"].dataType, T.IntegralType)
    rows = p.block().select(F.col("id").cast("long" if whole else "string").alias("id"), *p.features, _weight(p).alias("__w"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                ids, *cols, w = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
                kept = pickle.dumps((ids if whole else ids.tolist(), np.stack(cols), w), 5)
                yield pa.RecordBatch.from_arrays([pa.array([kept], pa.binary())], ["block"])

    return Held(p, rows.mapInArrow(pack, "block binary").rdd.map(lambda r: bytes(r[0])).persist(StorageLevel.DISK_ONLY))


@contextmanager
def holding(p: PartySpec | Held) -> Iterator[Held]:
    """The blocks of a party, given up afterwards unless they were held before."""
    held = p if isinstance(p, Held) else hold(p)
    try:
        yield held
    finally:
        if held is not p:
            held.release()


def _hashes(ids: np.ndarray | list[str]) -> Callable[[Sequence[object]], np.ndarray]:
    """For common parts, the hashes of these ids; whole ids are taken apart once for all parts."""
    if isinstance(ids, np.ndarray) and (ids >= 0).all():
        spelled = spell(ids)
        return lambda parts: u52_spelled(parts, spelled)
    names = list(map(str, ids))
    return lambda parts: u52_many(parts, names)


def least_key(u: np.ndarray, mass: np.ndarray, ids: Sequence) -> tuple[int | None, float]:
    """The row of the least ``-ln(u) / mass`` among those with a mass, ties to the least id, and its key.

    ``-ln(u)`` is at least ``1 - u``, so logarithms are taken only of rows that can still win.
    """
    some = np.flatnonzero(mass > 0)
    if not len(some):
        return None, np.inf
    bound = (1 - u[some]) / mass[some]
    able = some[bound <= -np.log(u[(j := some[bound.argmin()])]) / mass[j] * (1 + 1e-12)]
    key = -np.log(u[able]) / mass[able]
    best = able[key == key.min()]
    return (int(best[0]) if len(best) == 1 else min(best.tolist(), key=lambda j: ids[j])), float(key.min())


def d2_seeds(p: PartySpec | Held, k: int, seeds: Sequence[str]) -> list[np.ndarray]:
    """For each start k seeds, each drawn by its (weighted) squared distance to the ones before, the first by weight alone.

    Where all rows are seeds already, further ones are drawn by weight alone. A task hands on its winner of each start.
    """
    with holding(p) as held:
        out = [np.zeros((0, len(held.features))) for _ in seeds]
        for i in range(k):

            def race(blocks: Iterator[tuple], out=out, i=i) -> Iterable[tuple]:
                won: dict[tuple[int, int], tuple] = {}
                for ids, x, wt in blocks:
                    hashes = _hashes(ids)
                    for r, seed in enumerate(seeds):
                        u = (hashes([seed, i]) + 0.5) / (1 << BITS)
                        mass = wt * (least_distances(x, out[r]) if len(out[r]) else 1.0)
                        free = int(not (mass > 0).any())  # draws by weight alone count where no row anywhere has a mass
                        at, key = least_key(u, wt if free else mass, ids)
                        if at is not None:
                            mine = (key, str(ids[at]), x[:, at].tolist())
                            won[r, free] = min(won.get((r, free), mine), mine)
                return list(won.items())

            found: dict[tuple[int, int], tuple] = {}
            for at, mine in held.each(race):
                found[at] = min(found.get(at, mine), mine)
            out = [np.vstack([c, [(found.get((r, 0)) or found[r, 1])[2]]]) for r, c in enumerate(out)]
        return out


def d2_centers(p: PartySpec | Held, k: int, seed: str = "d2") -> np.ndarray:
    return d2_seeds(p, k, [seed])[0]


def lloyd_many(p: PartySpec | Held, starts: Sequence[np.ndarray], iterations: int) -> list[np.ndarray]:
    """Lloyd steps of several starts on all rows, one scan a step; an empty cell keeps its centre, and starts that stand still end the work.

    Tasks hand on sums of their rows by start and cell.
    """
    starts = [np.array(c, float) for c in starts]
    with holding(p) as held:
        for _ in range(iterations):

            def partial(blocks: Iterator[tuple], starts=starts) -> Iterable[list[np.ndarray]]:
                sums = [np.zeros((len(c), c.shape[1] + 1)) for c in starts]
                for _, x, w in blocks:
                    add_cells(sums, x, w, starts)
                return [sums]

            sums = [np.zeros((len(c), c.shape[1] + 1)) for c in starts]
            for part in held.each(partial):
                for s, own in zip(sums, part, strict=True):
                    s += own
            moved, after = 0.0, []
            for c, s in zip(starts, sums, strict=True):
                full = s[:, -1] > 0
                new = np.where(full[:, None], s[:, :-1] / np.where(full, s[:, -1], 1)[:, None], c)
                moved = max(moved, float(np.abs(new - c).max(initial=0)))
                after.append(new)
            starts = after
            if moved < 1e-12:
                break
    return starts


def costs_many(df: DataFrame | Held, features: Sequence[str], models: Sequence[np.ndarray], weight: str | None = None) -> tuple[list[float], float]:
    """Sum of (weighted) squared distances to the nearest centre for many center sets, broadcast once, and the weight of all rows; held rows bring their own weights."""
    if not isinstance(df, Held):
        with holding(PartySpec("rows", df.withColumn("id", F.lit(0)) if "id" not in df.columns else df, tuple(features), weight=weight)) as held:
            return costs_many(held, features, models)
    if list(features) != df.features:
        raise ValueError(f"the rows hold {df.features}, not {list(features)}")
    sent = df.blocks.context.broadcast([np.asarray(c, float) for c in models])

    def partial(blocks: Iterator[tuple]) -> Iterable[np.ndarray]:
        total, n = np.zeros(len(sent.value)), 0.0
        for _, x, w in blocks:
            n += w.sum()
            total += cost_sums(x.T, w, sent.value)
        return [np.append(total, n)]

    sums = sum(df.each(partial), np.zeros(len(models) + 1))
    sent.destroy()
    return sums[:-1].tolist(), float(sums[-1])


def full_centers(p: PartySpec | Held, k: int, *, restarts: int = 3, iterations: int = 20, seed: str = "full") -> np.ndarray:
    """Seeding by squared distance and Lloyd steps on all rows: the start of the least cost."""
    with holding(p) as held:
        found = lloyd_many(held, d2_seeds(held, k, [f"{seed}-{r}" for r in range(restarts)]), iterations)
        return found[int(np.argmin(costs_many(held, held.features, found)[0]))]


def lloyd(p: PartySpec | Held, centers: np.ndarray, iterations: int) -> np.ndarray:
    """Lloyd steps on all rows; an empty cell keeps its centre."""
    return lloyd_many(p, [centers], iterations)[0]


def scalable_centers(p: PartySpec | Held, k: int, seed: str = "scalable", rounds: int = 3) -> np.ndarray:
    """A few rounds of over-sampling (2 k rows each in the mean, by weighted squared distance), then weighted seeding of the candidates."""
    with holding(p) as held:
        chosen = first_centers(held.party, 1)
        for r in range(rounds):

            def masses(blocks: Iterator[tuple], chosen=chosen) -> Iterable[float]:
                return [float(sum((least_distances(x, chosen) * w).sum() for _, x, w in blocks))]

            total = sum(held.each(masses))
            if not total:
                break

            def take(blocks: Iterator[tuple], chosen=chosen, r=r, share=2.0 * k / total) -> Iterable[tuple]:
                for ids, x, w in blocks:
                    hit = _hashes(ids)([seed, r]) < np.minimum(1.0, share * (least_distances(x, chosen) * w)) * float(1 << BITS)
                    yield from ((ids[j], *x[:, j].tolist()) for j in np.flatnonzero(hit).tolist())

            taken = sorted(held.each(take))
            if taken:
                chosen = np.vstack([chosen, np.array([x[1:] for x in taken], float)])

        def weights(blocks: Iterator[tuple]) -> Iterable[np.ndarray]:
            mass = np.zeros(len(chosen))
            for _, x, w in blocks:
                for low in range(0, len(w), BLOCK):
                    mass += np.bincount(vectors.nearest_rows(plain_distances(x[:, low : low + BLOCK].T, chosen)), w[low : low + BLOCK], len(chosen))
            return [mass]

        return fit_weighted(chosen, sum(held.each(weights), np.zeros(len(chosen))), k, seed=7, iterations=20)


def local_centers(p: PartySpec, k: int, clusterer: str = "scalable", *, iterations: int = 5, seed: str = "local") -> np.ndarray:
    with holding(p) as held:
        start = {"first": lambda h, k: first_centers(h.party, k), "farthest": lambda h, k: farthest_centers(h.party, k), "d2seed": lambda h, k: d2_centers(h, k, seed), "scalable": lambda h, k: scalable_centers(h, k, seed)}[clusterer](held, k)
        return lloyd(held, start, iterations)


def distances(x: np.ndarray, centers: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(1)[:, None] - 2 * x @ centers.T + (centers * centers).sum(1)[None, :], 0.0)


def plain_distances(x: np.ndarray, centers: np.ndarray) -> np.ndarray:
    """Squared distances by differences, column by column, as the engine's expressions take them."""
    cols, part = np.ascontiguousarray(x.T), np.empty(len(x))
    out = np.zeros((len(centers), len(x)))
    for k, c in enumerate(centers):
        for j, col in enumerate(cols):
            np.subtract(col, c[j], out=part)
            np.multiply(part, part, out=part)
            out[k] += part
    return out.T


def least_distances(x: np.ndarray, centers: np.ndarray) -> np.ndarray:
    """Squared distance of each column of x (features x rows) to its nearest centre, by differences, a block of rows at a time."""
    return np.concatenate([np.zeros(0), *(plain_distances(x[:, low : low + STRIP].T, centers).T.min(0) for low in range(0, x.shape[1], STRIP))])


def add_cells(sums: Sequence[np.ndarray], x: np.ndarray, w: np.ndarray, starts: Sequence[np.ndarray]) -> None:
    """Adds the weighted sums of the columns of x (features x rows) by their nearest centre, and last the weight of each cell, for each start.

    One product for all starts shows the nearest centre of nearly all rows; rows that it leaves within rounding or within the limit of a tie are
    decided by differences, so cells are those of ``plain_distances`` and ``vectors.nearest_rows``.
    """
    stacked = np.vstack([np.hstack([-2 * c, (c * c).sum(1)[:, None]]) for c in starts])
    reach = float(stacked[:, -1].max(initial=0))
    for low in range(0, x.shape[1], BLOCK):
        block, mass = x[:, low : low + BLOCK], w[low : low + BLOCK]
        laid, own = np.vstack([block, np.ones(len(mass))]), (block * block).sum(0)
        weighted, safe = (laid * mass).T, bool(np.isfinite(own).all() and np.isfinite(reach))
        if not safe:
            for s, c in zip(sums, starts, strict=True):
                cell = vectors.nearest_rows(plain_distances(block.T, c))
                s += np.stack([np.bincount(cell, weighted[:, j], len(c)) for j in range(s.shape[1])], 1)
            continue
        product, at = stacked @ laid, 0
        slack = 1e-12 * (own + reach)
        for s, c in zip(sums, starts, strict=True):
            part = product[at : at + len(c)]
            at += len(c)
            least = part.min(0)
            near = part <= least + (slack + 2 * vectors.TIE * np.maximum(least + own, 0.0))
            member = near.astype(float)
            if np.count_nonzero(near) != len(mass):
                unclear = np.flatnonzero(near.sum(0) != 1)
                member[:, unclear] = 0.0
                member[vectors.nearest_rows(plain_distances(block[:, unclear].T, c)), unclear] = 1.0
            s += member @ weighted


def cost_sums(x: np.ndarray, w: np.ndarray, models: Sequence[np.ndarray]) -> np.ndarray:
    """Weighted sum of squared distances to the nearest centre, for each of many center sets.

    The centres of a few models at a time meet a block of rows in one product, laid centre by row, so that the minimum runs along rows.
    """
    total = np.zeros(len(models))
    by_size: dict[int, list[int]] = {}
    for i, c in enumerate(models):
        by_size.setdefault(len(c), []).append(i)
    for low in range(0, len(x), BLOCK):
        block, mass = x[low : low + BLOCK], w[low : low + BLOCK]
        laid, own = np.vstack([block.T, np.ones(len(block))]), (block * block).sum(1)
        for k, ids in by_size.items():
            for at in range(0, len(ids), TOGETHER):
                few = ids[at : at + TOGETHER]
                centers = np.vstack([models[i] for i in few])
                product = np.hstack([-2 * centers, (centers * centers).sum(1)[:, None]]) @ laid
                near = product.reshape(len(few), k, len(block)).min(1) + own
                total[few] += np.maximum(near, 0.0) @ mass
    return total


def seed_weighted(x: np.ndarray, w: np.ndarray, k: int, seed: int) -> np.ndarray:
    rng = np.random.default_rng(seed)
    centers = [x[rng.choice(len(x), p=w / w.sum())]]
    d2 = ((x - centers[0]) ** 2).sum(1)
    while len(centers) < min(k, len(x)):
        mass = w * d2
        i = rng.choice(len(x), p=mass / mass.sum()) if mass.sum() > 0 else int(rng.integers(len(x)))
        centers.append(x[i])
        d2 = np.minimum(d2, ((x - x[i]) ** 2).sum(1))
    return np.array(centers)


def fit_weighted(x: np.ndarray, w: np.ndarray, k: int, *, seed: int = 0, iterations: int = 25, start: np.ndarray | None = None) -> np.ndarray:
    """Weighted seeding by squared distance and Lloyd steps; a few thousand rows on one machine."""
    good = w > 0
    x, w = x[good], w[good]
    centers = start.copy() if start is not None else seed_weighted(x, w, k, seed)
    for _ in range(iterations):
        cell = distances(x, centers).argmin(1)
        mass = np.bincount(cell, w, len(centers))
        sums = np.stack([np.bincount(cell, w * x[:, j], len(centers)) for j in range(x.shape[1])], 1)
        new = np.where(mass[:, None] > 0, sums / np.where(mass > 0, mass, 1)[:, None], centers)
        if np.allclose(new, centers, rtol=0, atol=1e-12):
            break
        centers = new
    return centers
