"""The solver's backend over DataFrames: vectors live in the frames of variables and rows, scalars come to the driver.

For graphs whose vertex vectors no driver should hold. Per iteration: the weights and both transposed products end in one
frame of variables with the direction, whose extremes are observed as it is written; one forward product per side extends the
row frames; the step search reads those, all trial steps of a pass as columns of one aggregate, and what it learns of the
accepted step is the next iteration's statistics. Frames are written to the shared folder every ``checkpoint_every``
iterations and persisted in between, so a lost executor costs at most the iterations since; written frames are deleted as
soon as newer ones stand, but for the best point kept.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from poslp.plans.shared import discard, materialise
from poslp.plans.solver import Direction, Stats
from poslp.plans.steps import Trial


@dataclass
class Side:
    """A frame side (op and rows) or, with a target, the objective row."""

    op: object = None
    rows: DataFrame | None = None
    target: float | None = None


class SparkBackend:
    def __init__(self, variables: DataFrame, packing: Side, covering: Side, column_max: float | str = 1.0, checkpoint_every: int = 1):
        """variables: the frame with ``var``; column_max: the largest packing entry of a variable, or its column."""
        self.variables, self.sides = variables, (packing, covering)
        self.n = variables.count()
        counts = [1 if s.target else s.rows.count() for s in self.sides]
        self.rows, self.one_row, self.column_max, self.every = sum(counts), min(counts) == 1, column_max, checkpoint_every
        self.structure = [c for c in variables.columns]
        self.iter = 0
        self.persisted: list[DataFrame] = []
        self.written: list[DataFrame] = []  # what the current frames read
        self.best: DataFrame | None = None
        self.dropping = False

    def _hold(self, df: DataFrame, name: str) -> DataFrame:
        if self.iter % self.every == 0:
            df = materialise(df, name)
            self.written.append(df)
            return df
        df = df.persist()
        self.persisted.append(df)
        return df

    def _discard(self, old: list[DataFrame]) -> None:
        kept = getattr(self.best, "written_path", None)
        discard(*(f for f in old if f.written_path != kept))

    def start(self, eps: float) -> None:
        top = F.col(self.column_max) if isinstance(self.column_max, str) else F.lit(float(self.column_max))
        v = self.variables.withColumn("x", F.lit(eps / max(1, self.n)) / top)
        self.v = self._hold(v, "x0")
        self.source = self.v
        self.frames = [None if s.target else self._hold(s.op.forward(self.v.withColumn("val", F.col("x")), s.rows, ["val"]), "row0") for s in self.sides]
        self.sum_x = self.v.agg(F.sum("x")).first()[0]
        self.sum_d, self.known, self.tried = 0.0, None, {}

    def _scan(self, aggs: list[list]) -> list[list]:
        """One row per frame side, in one job; aggs: columns for the packing and the covering frame."""
        parts = [f.agg(F.array(*[c.cast("double") for c in a]).alias("a")).select(F.lit(i).alias("side"), "a") for i, (f, a) in enumerate(zip(self.frames, aggs)) if f is not None]
        out: list[list] = [[], []]
        if parts:
            both = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
            for r in both.collect():
                out[r["side"]] = r["a"]
        return out

    def _active(self, c):
        """Covering values that count: all, or those of rows below one where satisfied rows are dropped."""
        return F.when(F.col("val") < 1, c) if self.dropping else c

    def drop(self) -> int:
        self.dropping, self.known = True, None
        return 1

    def stats(self, eta: float) -> Stats:
        if self.known is not None:
            return self.known
        e, val = F.lit(float(eta)), F.col("val")
        tops = self._scan([[F.max(val)], [F.min(val), F.min(self._active(val))]])
        my = self.sum_x / self.sides[0].target if self.sides[0].target else tops[0][0]
        least, mz = [self.sum_x / self.sides[1].target] * 2 if self.sides[1].target else tops[1]
        if mz is None:
            mz = math.inf
        sums = self._scan([[F.sum(F.exp(e * (val - F.lit(my))))], [F.sum(self._active(F.exp(-e * (val - F.lit(mz)))))] if mz < math.inf else [F.lit(None)]])
        ly, lz = [math.log(a[0]) if a and a[0] else 0.0 for a in sums]
        return Stats(my, my + ly / eta, least, mz - lz / eta, self.sum_x)

    def direction(self, eta: float, s: Stats, scale: float) -> Direction:
        begun = time.perf_counter()
        e, v = F.lit(float(eta)), self.v
        for side, frame, name, sign, lse in zip(self.sides, self.frames, ("g", "h"), (1, -1), (s.lse_y, s.lse_z)):
            if side.target:
                v = v.withColumn(name, F.lit(1.0 / side.target))
            else:
                w = F.exp(sign * e * (F.col("val") - F.lit(lse)))
                v = side.op.back(v, frame.withColumn("w", F.coalesce(self._active(w), F.lit(0.0)) if sign < 0 else w), "w", name)
        d = F.when(F.col("h") > 0, F.greatest(F.lit(0.0), 1 - F.col("g") / F.col("h"))).otherwise(0.0) * F.col("x") * F.lit(scale / (2 * eta))
        old, spent = self.persisted, self.written
        self.persisted, self.written = [], []
        seen = Observation("direction")
        v = v.select(*self.structure, "x", "g", "h", d.alias("d")).observe(seen, F.max("d").alias("max_d"), F.sum("d").alias("sum_d"), F.min("g").alias("min_g"), F.max("h").alias("max_h"))
        self.v = self._hold(v, "direction")
        if self.v in self.persisted:
            self.v.count()
        self.source, r = self.v, [seen.get[c] for c in ("max_d", "sum_d", "min_g", "max_h")]
        self.frames = [None if side.target else self._hold(side.op.forward(self.v.withColumn("inc", F.col("d")), frame, ["inc"]), "rows") for side, frame in zip(self.sides, self.frames)]
        if self.written:
            self._discard(spent)
        else:
            self.written = spent
        for f in self.frames:
            if f is not None and f in self.persisted:
                f.count()
        for f in old:
            f.unpersist()
        self.v = self.v.drop("g", "h")
        self.sum_d = r[1]
        self.iter += 1
        self.t_matvec, self.t_vec = time.perf_counter() - begun, 0.0
        return Direction(*r)

    def lanes(self, eta: float, s: Stats, alphas: list[float]) -> list[Trial]:
        e, n = F.lit(float(eta)), len(alphas)
        at = [F.col("val") + F.lit(float(a)) * F.col("inc") for a in alphas]
        tops = self._scan([[F.max(c) for c in at], [F.min(self._active(c)) for c in at] + [F.min(c) for c in at]])
        tops = [t or [(self.sum_x + a * self.sum_d) / side.target for a in alphas] * 2 for t, side in zip(tops, self.sides)]
        least, tops = tops[1][n:], [tops[0][:n], tops[1][:n]]
        sums = []
        for sign, top in zip((1, -1), tops):
            exps = [F.exp(sign * e * (c - F.lit(t))) for c, t in zip(at, top)]
            both = [F.sum(x) for x in exps] + [F.sum(x * F.col("inc")) for x in exps]
            if sign < 0 and self.dropping:
                both = [F.sum(self._active(x)) for x in exps] + [F.sum(self._active(x * F.col("inc"))) for x in exps]
            sums.append(both)
        sums = self._scan(sums)
        out = []
        for k, a in enumerate(alphas):
            log, slope = [], []
            for got, side in zip(sums, self.sides):
                log.append(math.log(got[k]) / eta if got else 0.0)
                slope.append(got[n + k] / got[k] if got else self.sum_d / side.target)
            out.append(Trial(a, tops[1][k] - log[1] - s.lse_z, tops[0][k] + log[0] - s.lse_y, slope[1], slope[0], least[k]))
            self.tried[a] = Stats(tops[0][k], tops[0][k] + log[0], least[k], tops[1][k] - log[1], self.sum_x + a * self.sum_d)
        return out

    def advance(self, alpha: float) -> None:
        self.v = self.v.withColumn("x", F.col("x") + F.lit(float(alpha)) * F.col("d")).drop("d")
        self.frames = [None if f is None else f.withColumn("val", F.col("val") + F.lit(float(alpha)) * F.col("inc")).drop("inc") for f in self.frames]
        self.known, self.tried = (None if self.dropping else self.tried.get(alpha)), {}
        self.sum_x += alpha * self.sum_d

    def keep(self) -> DataFrame:
        """The point now; the one kept before goes, if nothing else reads it."""
        old, self.best = self.best, self.source
        if old is not None and old is not self.source and old not in self.written:
            discard(old)
        out = self.v.select(*self.structure, "x")
        out.written_path = getattr(self.source, "written_path", None)
        out.release = lambda: discard(out)
        return out

    def close(self) -> None:
        """Row frames stay for lower bounds; they go with the shared folder's next cleaning by release()."""
        for f in self.persisted:
            if f is not self.source:
                f.unpersist()
