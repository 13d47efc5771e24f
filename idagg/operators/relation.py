"""Overlap, Jaccard and containment from two register arrays by joint maximum likelihood.

The two arrays' aligned registers are reduced to a histogram of value pairs: about a hundred cells whatever the arrays' and the streams'
sizes. A fit works on one pair's cells in one Python call, so many pairs or groups run side by side; nothing iterates over jobs. A fit
that isn't converged is invalid: its readouts are NULL, and nothing else is put in their place.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from idagg.operators.registers import merge_registers, pack
from idagg.sources.shared import written
from idagg.spec import DEFAULT_P

MATRIX_STREAMS = 2_000  # streams that are all paired with each other; of more, the pairs wanted are given

FIT_SCHEMA = "n10 double, n01 double, n11 double, reason string, iterations int, boundary string, residual double, valid boolean"


def pair_cells(regs: DataFrame, a: str, b: str, keys: list[str], stream: str = "stream_id") -> DataFrame:
    """(keys, u, v, h) for streams a and b of one register relation, without the cell of registers empty in both: one pass over the
    relation, however it was made."""
    s, r = F.col(stream), F.col("r")
    x = regs.where(s.isin(a, b)).groupBy(*keys, "j").agg(
        F.coalesce(F.max(F.when(s == a, r)), F.lit(0)).alias("u"), F.coalesce(F.max(F.when(s == b, r)), F.lit(0)).alias("v"))
    return x.groupBy(*keys, "u", "v").agg(F.count("*").alias("h"))


def pair_histogram(a: DataFrame, b: DataFrame, keys: list[str], p: int = DEFAULT_P, complete: bool = True) -> DataFrame:
    """(keys, u, v, h): how many registers have value u in a and v in b; counts of a key sum to m.

    One conditional maximum by (keys, j) aligns the arrays; registers empty in both are what is left of m (added where complete)."""
    x = a.select(*keys, "j", F.col("r").alias("__u"), F.lit(0).alias("__v")).unionByName(b.select(*keys, "j", F.lit(0).alias("__u"), F.col("r").alias("__v")))
    cells = x.groupBy(*keys, "j").agg(F.max("__u").alias("u"), F.max("__v").alias("v")).groupBy(*keys, "u", "v").agg(F.count("*").alias("h"))
    if not complete:
        return cells
    rest = cells.groupBy(*keys).agg((F.lit(1 << p) - F.sum("h")).alias("h")).where("h > 0").select(*keys, F.lit(0).alias("u"), F.lit(0).alias("v"), "h")
    return cells.unionByName(rest)


def _weights(k: np.ndarray, q: int) -> np.ndarray:
    """P(one item's rank exceeds k) under q hash bits; 0 from the largest rank on."""
    return np.where(k > q, 0.0, np.exp2(-np.minimum(k, q).astype(float)))


def log_cells(n: np.ndarray, u: np.ndarray, v: np.ndarray, m: int, q: int) -> np.ndarray:
    """Log probability that a register pair reads (u, v), items falling on registers as independent Poisson counts.

    n: items only in a, only in b, in both. With lower values L = min(u, v), the pair's distribution function is
    exp(-(n10 w(u) + n01 w(v) + n11 w(L)) / m), and a cell is its difference in both directions, kept in factored form so that small
    probabilities don't cancel."""
    a, b, c = n / m
    wu, wv = _weights(u, q), _weights(v, q)
    du = np.where(u > 0, _weights(u - 1, q) - wu, np.inf)  # step down in u; infinite where there is nothing below
    dv = np.where(v > 0, _weights(v - 1, q) - wv, np.inf)

    def drop(rate, d):  # log(1 - exp(-rate * d)), 0 where d is infinite
        with np.errstate(divide="ignore", invalid="ignore"):
            x = np.where(np.isinf(d), np.inf, rate * d)
            return np.where(np.isinf(d), 0.0, np.log(-np.expm1(-x)))

    base = -(a * wu + b * wv + c * np.where(u < v, wu, wv))
    out = np.empty(len(u))
    lt, gt, eq = u < v, u > v, u == v
    out[lt] = base[lt] + drop(a + c, du[lt]) + drop(b, dv[lt])  # both-items set the smaller value
    out[gt] = base[gt] + drop(a, du[gt]) + drop(b + c, dv[gt])
    if eq.any():
        d = du[eq]
        zero = u[eq] == 0
        d = np.where(zero, 1.0, d)
        # 1 - e^{-(a+c)d} - e^{-(b+c)d} + e^{-(a+b+c)d} = (1-e^{-cd}) + e^{-cd}(1-e^{-ad})(1-e^{-bd})
        with np.errstate(divide="ignore", invalid="ignore"):
            val = -np.expm1(-c * d) + np.exp(-c * d) * np.expm1(-a * d) * np.expm1(-b * d)
            out[eq] = base[eq] + np.where(zero, 0.0, np.log(val))
    return out


def log_likelihood(n: np.ndarray, u: np.ndarray, v: np.ndarray, h: np.ndarray, m: int, q: int) -> float:
    with np.errstate(all="ignore"):
        x = float(np.dot(h, log_cells(np.asarray(n, float), u, v, m, q)))
    return x if math.isfinite(x) else -math.inf


def gradient(n: np.ndarray, u, v, h, m: int, q: int) -> np.ndarray:
    """By central differences in each coordinate, one-sided at zero."""
    n = np.asarray(n, float)
    g = np.empty(3)
    for k in range(3):
        e = max(1e-4 * n[k], 1e-4)
        hi, lo = n.copy(), n.copy()
        hi[k] += e
        lo[k] = max(0.0, n[k] - e)
        g[k] = (log_likelihood(hi, u, v, h, m, q) - log_likelihood(lo, u, v, h, m, q)) / (hi[k] - lo[k])
    return g


def _linear_count(z: np.ndarray, h: np.ndarray, m: int) -> float:
    from idagg.functions.estimate import alpha

    s, e = float(np.dot(h, np.exp2(-z.astype(float)))), float(h[z == 0].sum())
    raw = alpha(m) * m * m / s
    return m * math.log(m / e) if raw <= 2.5 * m and e else raw


def fit_regions(u, v, h, m: int, sweeps: int = 24, tol: float = 1e-3, kkt: float = 5e-4) -> dict:
    """Sizes of the three regions at the likelihood's maximum, with diagnostics.

    Coordinate ascent: a coordinate moves by golden-section search of its logarithm around its value, or to zero where that is as
    likely; only moves that don't lower the likelihood count. Converged means that no coordinate moves by more than tol (relative) and the
    scaled gradient vanishes inside (n times the derivative over m) or points outwards at zero. The start is a rough difference of counts."""
    u, v, h = np.asarray(u, np.int64), np.asarray(v, np.int64), np.asarray(h, float)
    q = 64 - int(math.log2(m))
    if not (u.any() or v.any()):
        return dict(n10=0.0, n01=0.0, n11=0.0, reason="empty", iterations=0, boundary="n10,n01,n11", residual=0.0, valid=True)
    na, nb, nu = _linear_count(u, h, m), _linear_count(v, h, m), _linear_count(np.maximum(u, v), h, m)
    both = max(1.0, na + nb - nu)
    n = np.array([max(1.0, na - both), max(1.0, nb - both), both])
    best = log_likelihood(n, u, v, h, m, q)
    names, reason, residual, done = ("n10", "n01", "n11"), "sweeps", math.inf, 0
    reach = np.full(3, 3.0)  # of each coordinate's search, on the log scale; it narrows while the optimum stays well inside
    for done in range(1, sweeps + 1):
        before = n.copy()
        for k in range(3):
            found = _line(n, k, reach[k], u, v, h, m, q)
            moved = abs(math.log(max(found, 1e-300) / max(n[k], 1e-2)))
            reach[k] = 3.0 if moved > 0.9 * reach[k] else min(3.0, max(0.01, 4 * moved))
            for cand in (0.0, found):
                trial = n.copy()
                trial[k] = cand
                x = log_likelihood(trial, u, v, h, m, q)
                if x > best or (x == best and cand == 0.0):
                    n, best = trial, x
        if np.all(np.abs(n - before) <= tol * np.maximum(1.0, np.abs(before))):
            residual = _residual(n, u, v, h, m, q)
            if residual <= kkt:
                reason = "converged"
                break
    else:
        done = sweeps
        if sweeps:
            residual = _residual(n, u, v, h, m, q)
    ok = reason == "converged" and math.isfinite(best) and bool(np.isfinite(n).all())
    return dict(
        n10=float(n[0]), n01=float(n[1]), n11=float(n[2]), reason=reason, iterations=done if sweeps else 0,
        boundary=",".join(c for c, x in zip(names, n, strict=True) if x == 0), residual=float(residual), valid=ok)


def _residual(n, u, v, h, m, q) -> float:
    g = gradient(n, u, v, h, m, q)
    if not np.isfinite(g).all():
        return math.inf
    return float(max(abs(n[k] * g[k]) / m if n[k] > 0 else max(0.0, g[k]) / m for k in range(3)))


def _line(n, k, reach, u, v, h, m, q) -> float:
    """The best value of one coordinate by golden section on a log scale, around where it is (around 0.01 where it is zero)."""
    x = n.copy()

    def f(t):
        x[k] = math.exp(t)
        return log_likelihood(x, u, v, h, m, q)

    mid = math.log(max(n[k], 1e-2))
    lo, hi = mid - reach, mid + reach
    phi = (math.sqrt(5) - 1) / 2
    a, b = hi - phi * (hi - lo), lo + phi * (hi - lo)
    fa, fb = f(a), f(b)
    while hi - lo > 1e-5:
        if fa >= fb:
            hi, b, fb = b, a, fa
            a = hi - phi * (hi - lo)
            fa = f(a)
        else:
            lo, a, fa = a, b, fb
            b = lo + phi * (hi - lo)
            fb = f(b)
    return math.exp((lo + hi) / 2)


def fit_pairs(hist: DataFrame, keys: list[str], p: int = DEFAULT_P, sweeps: int = 24, tol: float = 1e-3, kkt: float = 5e-4) -> DataFrame:
    """(keys, regions and diagnostics) of each pair's histogram; registers that it leaves out are empty in both."""
    m = 1 << p

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        u, v, h = (np.append(pdf[c].to_numpy(), x) for c, x in (("u", 0), ("v", 0), ("h", m - int(pdf["h"].sum()))))
        keep = h > 0
        got = fit_regions(u[keep], v[keep], h[keep], m, sweeps, tol, kkt)
        return pd.DataFrame([{**{k: pdf[k].iloc[0] for k in keys}, **got}])

    names = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in hist.schema if f.name in keys)
    # cells are few bytes and much work: a stated number of tasks, which adaptive execution doesn't merge into one
    dealt = hist.repartition(int(hist.sparkSession.conf.get("spark.sql.shuffle.partitions")), *keys)
    return dealt.groupBy(*keys).applyInPandas(one, f"{names}, {FIT_SCHEMA}").select(*keys, *[c.split()[0] for c in FIT_SCHEMA.split(", ")])


def readouts(fits: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, jaccard, containment_ab, containment_ba, overlap, only_a, only_b, valid); NULL where the fit is invalid, 0 where a base is empty."""
    a, b, c = F.col("n10"), F.col("n01"), F.col("n11")

    def ratio(x, y):
        return F.when(F.col("valid"), F.when(y == 0, 0.0).otherwise(x / y))

    return fits.select(
        *keys, ratio(c, a + b + c).alias("jaccard"), ratio(c, a + c).alias("containment_ab"), ratio(c, b + c).alias("containment_ba"),
        F.when(F.col("valid"), c).alias("overlap"), F.when(F.col("valid"), a).alias("only_a"), F.when(F.col("valid"), b).alias("only_b"), "valid")


def relate(regs: DataFrame, a: str, b: str, keys: list[str] | None = None, p: int = DEFAULT_P, stream: str = "stream_id", **fit) -> DataFrame:
    """Readouts for streams a and b of a register relation, by keys if any."""
    keys = keys or []
    named = [*keys, "pair_id"]
    cells = pair_cells(regs, a, b, keys, stream).withColumn("pair_id", F.lit(f"{a}|{b}"))
    return readouts(fit_pairs(cells, named, p, **fit), named)


def relation_matrix(regs: DataFrame, stream: str = "stream_id", p: int = DEFAULT_P, pairs: DataFrame | None = None, **fit) -> DataFrame:
    """Readouts of pairs of streams from their states, which are written once as m bytes each; a pair is a row with two of them and is fitted there.

    pairs (a, b), of any number, lists those wanted; a stream in it that was never seen has an empty state. Without it each pair a < b of
    at most MATRIX_STREAMS streams is read, and more streams than that are an error, as their pairs grow with the square."""
    m = 1 << p
    s = written(pack(merge_registers(regs.select(F.col(stream).alias("a"), "j", "r"), ["a"]), ["a"], p), "matrix")
    if pairs is None:
        n = s.count()
        if n > MATRIX_STREAMS:
            raise ValueError(f"{n} streams have too many pairs: give the pairs wanted")
        seen = s.select("a")
        pairs = seen.join(seen.withColumnRenamed("a", "b"), F.col("a") < F.col("b"))
    x = pairs.select("a", "b").join(s.withColumnRenamed("state", "__x"), "a", "left").join(s.withColumnsRenamed({"a": "b", "state": "__y"}), "b", "left")
    names = [c.split()[0] for c in FIT_SCHEMA.split(", ")]

    def fitted(batches):
        for pdf in batches:
            out = []
            for both in zip(pdf["__x"], pdf["__y"], strict=True):
                u, v = (np.zeros(m, np.int64) if t is None else np.frombuffer(t, np.uint8).astype(np.int64) for t in both)
                cells, h = np.unique(u << 8 | v, return_counts=True)
                out.append(fit_regions(cells >> 8, cells & 255, h, m, **fit))
            yield pd.concat([pdf[["a", "b"]].reset_index(drop=True), pd.DataFrame(out, columns=names)], axis=1)

    keys = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in x.select("a", "b").schema)
    # rows are few and their work is much, as in fit_pairs
    dealt = x.repartition(int(regs.sparkSession.conf.get("spark.sql.shuffle.partitions")), "a", "b")
    return readouts(dealt.mapInPandas(fitted, f"{keys}, {FIT_SCHEMA}"), ["a", "b"])


def inclusion_exclusion(na: float, nb: float, nu: float) -> float:
    """A comparator only: no readout falls back to it."""
    return na + nb - nu
