"""SQL twins: the methods spelled as DuckDB common table expressions, by other routes than the engine's where there are any.

Scores come from Gram-Schmidt chains instead of whiteners, samples from one running sum instead of buckets, least squares
from determinants instead of factorisations.
"""

from __future__ import annotations

from collections.abc import Sequence

from vpcoreset.functions.rng import place_sql, u52_sql
from vpcoreset.sources.fixtures import FIXTURES, wide_sql


def columns(name: str) -> list[list[str]]:
    """Matrix columns of each party, the label with the last one."""
    f = FIXTURES[name]
    out = [list(names) for names, _ in f.parties]
    if f.label:
        out[-1].append(f.label)
    return out


class Chain:
    """A WITH clause that grows; each step has a name."""

    def __init__(self):
        self.steps: list[str] = []

    def add(self, name: str, sql: str) -> str:
        self.steps.append(f"{name} AS ({sql})")
        return name

    def select(self, sql: str) -> str:
        return ("WITH RECURSIVE " if any("UNION ALL SELECT s + 1" in x for x in self.steps) else "WITH ") + ",\n".join(self.steps) + "\n" + sql

    def wide(self, fixture: str, standard: bool = True) -> str:
        self.add("w", wide_sql(fixture))
        if not standard:
            return "w"
        cols = [c for block in columns(fixture) for c in block]
        scaled = ", ".join(f"CASE WHEN stddev_pop({c}) OVER () > 0 THEN ({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER () ELSE 0.0 END AS {c}" for c in cols)
        return self.add("z", f"SELECT id, {scaled} FROM w")

    def leverage(self, prefix: str, rel: str, cols: Sequence[str], weight: str = "1.0") -> str:
        """(id, lev) by Gram-Schmidt; a column that adds nothing is skipped."""
        at = self.add(f"{prefix}0", f"SELECT id, {', '.join(f'sqrt({weight}) * {c} AS x{j}' for j, c in enumerate(cols))} FROM {rel}")
        for j in range(len(cols)):
            rest = "".join(f" - (sum(x{j} * u{i}) OVER ()) * u{i}" for i in range(j))
            again = self.add(f"{prefix}v{j}", f"SELECT *, x{j}{rest} AS v FROM {at}")
            unit = f"CASE WHEN sum(v * v) OVER () > 1e-10 * sum(x{j} * x{j}) OVER () THEN v / sqrt(sum(v * v) OVER ()) ELSE 0.0 END AS u{j}"
            at = self.add(f"{prefix}u{j}", f"SELECT * EXCLUDE (v), {unit} FROM {again}")
        return self.add(f"{prefix}l", f"SELECT id, {' + '.join(f'u{j} * u{j}' for j in range(len(cols)))} AS lev FROM {at}")

    def regression_scores(self, rel: str, blocks: Sequence[Sequence[str]]) -> str:
        parts = [f"SELECT id, {j} AS party, lev + 1.0 / count(*) OVER () AS score FROM {self.leverage(f'p{j}', rel, cols)}" for j, cols in enumerate(blocks)]
        return self.add("scores", " UNION ALL ".join(parts))

    def clusters(self, prefix: str, rel: str, cols: Sequence[str], k: int, iterations: int, start: str | None = None) -> tuple[str, str]:
        """(centres, assignment) of Lloyd steps from the rows of the k least ids, or from ``start``."""
        named = ", ".join(cols)
        c = start or self.add(f"{prefix}c0", f"SELECT CAST(row_number() OVER (ORDER BY id) - 1 AS INTEGER) AS cell, {named} FROM (SELECT id, {named} FROM {rel} ORDER BY id LIMIT {k})")
        for i in range(iterations + 1):
            d2 = " + ".join(f"(r.{x} - c.{x}) * (r.{x} - c.{x})" for x in cols)
            a = self.add(f"{prefix}a{i}", f"SELECT id, {named}, cell, d2 FROM (SELECT r.id, {', '.join(f'r.{x}' for x in cols)}, c.cell, {d2} AS d2, row_number() OVER (PARTITION BY r.id ORDER BY {d2}, c.cell) AS pos FROM {rel} r CROSS JOIN {c} c) WHERE pos = 1")
            if i < iterations:
                c = self.add(f"{prefix}c{i + 1}", f"SELECT o.cell, {', '.join(f'coalesce(n.{x}, o.{x}) AS {x}' for x in cols)} FROM {c} o LEFT JOIN (SELECT cell, {', '.join(f'avg({x}) AS {x}' for x in cols)} FROM {a} GROUP BY cell) n USING (cell)")
        return c, a

    def kmeans_scores(self, rel: str, blocks: Sequence[Sequence[str]], k: int, iterations: int, alpha: float = 1.0) -> str:
        parts = []
        for j, cols in enumerate(blocks):
            _, a = self.clusters(f"k{j}", rel, cols, k, iterations)
            parts.append(f"SELECT id, {j} AS party, {alpha} * (d2 / sum(d2) OVER () + sum(d2) OVER (PARTITION BY cell) / count(*) OVER (PARTITION BY cell) / sum(d2) OVER () + 2.0 / count(*) OVER (PARTITION BY cell)) AS score, cell FROM {a}")
        return self.add("scores", " UNION ALL ".join(parts))

    def draws(self, scores: str, m: int, seed: str, replicates: int = 1, p: int = 40, name: str = "") -> str:
        """(replicate, draw_no, party, id, t) of the integer sampler."""
        q, tot, par, thr, cdf = (f"{name}{x}" for x in ("q", "tot", "par", "thr", "cdf"))
        self.add(q, f"SELECT id, party, greatest(1, CAST(round(score * {1 << p}::DOUBLE) AS BIGINT)) AS q FROM {scores}")
        self.add(tot, f"SELECT party, qp, sum(qp) OVER (ORDER BY party) AS upto, sum(qp) OVER () AS grand FROM (SELECT party, CAST(sum(q) AS HUGEINT) AS qp FROM {q} GROUP BY party)")
        self.add(f"{name}num", f"SELECT CAST(a.range AS INTEGER) AS replicate, CAST(b.range AS INTEGER) AS draw_no FROM range({replicates}) a, range({m}) b")
        side = f"(CAST({u52_sql(repr(seed), repr('party'), 'replicate', 'draw_no')} AS HUGEINT) * grand) // 4503599627370496"
        self.add(par, f"SELECT replicate, draw_no, party, qp FROM {name}num, {tot} WHERE {side} >= upto - qp AND {side} < upto")
        self.add(thr, f"SELECT replicate, draw_no, party, (CAST({u52_sql(repr(seed), repr('row'), 'replicate', 'draw_no')} AS HUGEINT) * qp) // 4503599627370496 AS t FROM {par}")
        self.add(cdf, f"SELECT id, party, q, sum(CAST(q AS HUGEINT)) OVER (PARTITION BY party ORDER BY {place_sql('id')}, id) AS hi FROM {q}")
        return self.add(f"{name}draws", f"SELECT d.replicate, d.draw_no, d.party, c.id, d.t FROM {thr} d JOIN {cdf} c ON c.party = d.party AND d.t >= c.hi - c.q AND d.t < c.hi")

    def coreset(self, draws: str, m: int, name: str = "") -> str:
        """(replicate, id, draws, weight)."""
        return self.add(f"{name}coreset", f"SELECT d.replicate, d.id, d.draws, d.draws * (SELECT max(grand) FROM {name}tot)::DOUBLE / ({m}::DOUBLE * s.q) AS weight FROM (SELECT replicate, id, count(*) AS draws FROM {draws} GROUP BY 1, 2) d JOIN (SELECT id, sum(q) AS q FROM {name}q GROUP BY 1) s USING (id)")


def uniform(chain: Chain, rel: str, m: int, seed: str, replicates: int = 1, name: str = "u") -> str:
    scores = chain.add(f"{name}scores", f"SELECT id, 0 AS party, {2.0**-20!r} AS score FROM {rel}")
    return chain.coreset(chain.draws(scores, m, seed, replicates, p=20, name=name), m, name)


def gauss(chain: Chain, rel: str, cols: Sequence[str], label: str, lam: str, weight: str = "1.0", name: str = "ge", by: Sequence[str] = ()) -> str:
    """(by.., t0 .. td-1): ridge coefficients by Gauss-Jordan elimination of the normal equations, a step for each column."""
    d, keys = len(cols), "".join(f"{b}, " for b in by)
    sums = [f"sum({weight} * {cols[i]} * {cols[j]}){f' + {lam}' if i == j else ''} AS a{i}_{j}" for i in range(d) for j in range(d)]
    sums += [f"sum({weight} * {c} * {label}) AS a{i}_{d}" for i, c in enumerate(cols)]
    at = chain.add(f"{name}_s", f"SELECT {keys}{', '.join(sums)} FROM {rel}{' GROUP BY ' + ', '.join(by) if by else ''}")
    for k in range(d):
        row = [f"a{k}_{j} / a{k}_{k} AS a{k}_{j}" for j in range(k, d + 1)]
        rest = [f"a{i}_{j} - a{i}_{k} * a{k}_{j} / a{k}_{k} AS a{i}_{j}" for i in range(d) if i != k for j in range(k + 1, d + 1)]
        at = chain.add(f"{name}_{k}", f"SELECT {keys}{', '.join(row + rest)} FROM {at}")
    return chain.add(name, f"SELECT {keys}{', '.join(f'a{i}_{d} AS t{i}' for i in range(d))} FROM {at}")


def descent(chain: Chain, rel: str, cols: Sequence[str], label: str, l1: str, l2: str, sweeps: int, name: str = "cd") -> str:
    """(t0 .. td-1): elastic net by coordinate descent, a recursion step for each coordinate. The chain needs WITH RECURSIVE."""
    d = len(cols)
    sums = [f"sum({cols[i]} * {cols[j]}) AS g{i}_{j}" for i in range(d) for j in range(d)] + [f"sum({c} * {label}) AS b{i}" for i, c in enumerate(cols)]
    g = chain.add(f"{name}_g", f"SELECT {', '.join(sums)}, {l1} AS l1, {l2} AS l2 FROM {rel}")
    new = []
    for j in range(d):
        rest = f"(b{j}" + "".join(f" - g{j}_{i} * t{i}" for i in range(d) if i != j) + ")"
        new.append(f"CASE WHEN s % {d} = {j} THEN sign({rest}) * greatest(abs({rest}) - l1 / 2, 0) / (g{j}_{j} + l2) ELSE t{j} END AS t{j}")
    chain.add(name + "_r", f"SELECT 0 AS s, {', '.join(f'0.0::DOUBLE AS t{j}' for j in range(d))} UNION ALL SELECT s + 1, {', '.join(new)} FROM {name}_r, {g} WHERE s < {sweeps * d}")
    return chain.add(name, f"SELECT * FROM {name}_r WHERE s = {sweeps * d}")


def unpivot(cols: Sequence[str], rel: str, digits: int) -> str:
    return " UNION ALL ".join(f"SELECT '{c}' AS feature, round(t{i}, {digits}) AS coef FROM {rel}" for i, c in enumerate(cols))


def _det3(m: Sequence[Sequence[str]]) -> str:
    (a, b, c), (d, e, f), (g, h, i) = m
    return f"({a} * ({e} * {i} - {f} * {h}) - {b} * ({d} * {i} - {f} * {g}) + {c} * ({d} * {h} - {e} * {g}))"


def ridge3(chain: Chain, rel: str, cols: Sequence[str], label: str, lam: str, weight: str = "1.0", name: str = "ne") -> str:
    """(feature, coef) of three features by determinants of the normal equations."""
    sums = [f"sum({weight} * {a} * {b}){f' + {lam}' if i == j else ''} AS g{i}{j}" for i, a in enumerate(cols) for j, b in enumerate(cols)]
    sums += [f"sum({weight} * {a} * {label}) AS b{i}" for i, a in enumerate(cols)]
    chain.add(name, f"SELECT {', '.join(sums)} FROM {rel}")
    g = [[f"g{i}{j}" for j in range(3)] for i in range(3)]
    parts = []
    for k, c in enumerate(cols):
        swapped = [[f"b{i}" if j == k else g[i][j] for j in range(3)] for i in range(3)]
        parts.append(f"SELECT '{c}' AS feature, {_det3(swapped)} / {_det3(g)} AS coef FROM {name}")
    return " UNION ALL ".join(parts)
