"""Thinning of few long series in chunks that run in parallel, with lazy synchronisation of global sums.

A round hands each chunk the global pair sums, the raw statistic and a share of what is left of the bound. A chunk
thins against "the global sums with only me changing", with a halo of current values on both sides; its ends stay.
Then the exact global sums are rebuilt from the chunks' current values. If the bound is broken, each chunk takes back
its last removals by halves until it holds, so the result is always within the bound. What travels to the driver is five
sums per lag and series and the bound's arithmetic.
"""

from __future__ import annotations

import math
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernel import stats
from ..kernel.greedy import Rules, Series, thin
from .thinning import spread
from .thinning import thin as thin_whole

STATE = "series_id string, chunk long, pos long, raw double, cur double, alive boolean, seq int"


def _cut(df: DataFrame) -> DataFrame:
    """Cut the lineage in the shared checkpoint folder, so that a lost executor costs one round at most."""
    import tempfile

    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(df.sparkSession.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="checkpoints-"))
    return df.checkpoint(eager=True)


def _halo(state: DataFrame, chunk: int, reach: int) -> DataFrame:
    """Each chunk's rows and, marked, the nearest rows of its neighbours."""
    off = F.pmod(F.col("pos"), F.lit(chunk))
    own = state.withColumn("at", F.col("chunk")).withColumn("own", F.lit(True))
    left = state.where(off < reach).withColumn("at", F.col("chunk") - 1).withColumn("own", F.lit(False))
    right = state.where(off >= chunk - reach).withColumn("at", F.col("chunk") + 1).withColumn("own", F.lit(False))
    return own.unionByName(left.where("at >= 0")).unionByName(right)


def _sums(state: DataFrame, rules: Rules, chunk: int) -> dict[str, np.ndarray]:
    """Exact global sums per series: every chunk adds the pairs whose early member is its own."""
    k, lags = max(1, rules.window), np.array(rules.lags)
    reach = k * int(lags.max())

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos", kind="stable")
        own = g["own"].to_numpy()
        if not own.any():
            return pd.DataFrame({"series_id": [], "lag": [], "row": [], "v": []})
        first = g["pos"].to_numpy()[own][0]
        x = g["cur"].to_numpy()[g["pos"].to_numpy() >= first]
        n_own = int(own.sum())
        if k > 1:
            whole = len(x) // k * k
            w = x[:whole].reshape(-1, k)
            x, n_own = {"mean": w.mean, "sum": w.sum, "min": w.min, "max": w.max}[rules.agg](axis=1), n_own // k
        a, out = x[:n_own], np.zeros((6, len(lags)))
        for i, l in enumerate(lags):
            b = x[l : l + n_own]
            e = a[: len(b)]
            out[:, i] = len(b), e.sum(), b.sum(), (e * e).sum(), (b * b).sum(), (e * b).sum()
        rows, cols = np.indices(out.shape)
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "lag": cols.ravel(), "row": rows.ravel(), "v": out.ravel()})

    off = F.pmod(F.col("pos"), F.lit(chunk))
    both = state.select("series_id", "chunk", "pos", "cur").withColumn("own", F.lit(True))
    halo = both.where((off < reach) & (F.col("chunk") > 0)).withColumn("chunk", F.col("chunk") - 1).withColumn("own", F.lit(False))
    parts = both.unionByName(halo).groupBy("series_id", "chunk").applyInPandas(one, "series_id string, lag int, row int, v double")
    out: dict[str, np.ndarray] = {}
    for r in parts.groupBy("series_id", "lag", "row").agg(F.sum("v").alias("v")).collect():  # five sums per lag and series
        out.setdefault(r["series_id"], np.zeros((6, len(lags))))[r["row"], r["lag"]] = r["v"]
    return out


def _vector(sums: np.ndarray, rules: Rules) -> np.ndarray:
    r = stats.correlation(sums)
    return stats.partial(r) if rules.statistic == "partial" else r


def _redrawn(g: pd.DataFrame) -> np.ndarray:
    pos, alive = g["pos"].to_numpy(), g["alive"].to_numpy()
    return np.interp(pos, pos[alive], g["raw"].to_numpy()[alive])


def thin_chunked(df: DataFrame, rules: Rules, chunk: int = 100_000, share: float = 0.5, max_rounds: int = 10, max_rollbacks: int = 12) -> DataFrame:
    """Kept points ``(series_id, pos, value, n, deviation, rounds)`` of series cut into chunks of ``chunk`` positions.

    ``share`` of the remaining bound is released in each round, evenly over chunks. Chunks must be at least as long as
    the reach of the lags, and are cut at window borders. Ends of chunks stay. The global deviation is within the bound.
    """
    k = max(1, rules.window)
    reach = k * max(rules.lags)
    chunk = max(chunk // k * k, k)
    if chunk < reach:
        raise ValueError("chunks must be at least as long as the lags reach")
    base = df.select("series_id", F.floor(F.col("pos") / chunk).cast("long").alias("chunk"), "pos", F.col("value").cast("double").alias("raw"))
    mean = F.broadcast(base.groupBy("series_id").agg(F.avg("raw").alias("m"), F.count("*").alias("n")))
    state = _cut(base.join(mean, "series_id").select("series_id", "chunk", "pos", "raw", (F.col("raw") - F.col("m")).alias("cur"), F.lit(True).alias("alive"), F.lit(-1).alias("seq")))
    info = {r["series_id"]: (r["n"], r["chunks"]) for r in base.groupBy("series_id").agg(F.count("*").alias("n"), F.countDistinct("chunk").alias("chunks")).collect()}
    sums = _sums(state, rules, chunk)
    raw = {s: _vector(v, rules) for s, v in sums.items()}
    spent = {s: 0.0 for s in sums}
    local = replace(rules, ratio=math.inf, hops=rules.hops)
    rounds = 0
    p = dict.fromkeys(sums, share)
    for turn in range(max_rounds):
        budget = {s: p[s] * max(0.0, rules.eps - spent[s]) / info[s][1] for s in sums}
        if all(b < 1e-3 * rules.eps / info[s][1] for s, b in budget.items()):
            break
        told = df.sparkSession.sparkContext.broadcast((sums, raw, budget, spent, info))

        def run(g: pd.DataFrame) -> pd.DataFrame:
            s, (all_sums, all_raw, all_budget, all_spent, all_info) = g["series_id"].iloc[0], told.value
            g = g.sort_values("pos", kind="stable")
            own = g["own"].to_numpy()
            if not own.any():
                return g.iloc[:0][["series_id", "chunk", "pos", "raw", "cur", "alive", "seq"]]
            at = np.nonzero(own)[0]
            lo, hi = int(at[0]), int(at[-1]) + 1
            alive = g["alive"].to_numpy() | ~own
            x = Series(g["cur"].to_numpy(), local, lo, hi, int(g["pos"].iloc[0]), all_info[s][0], all_sums[s], all_raw[s], alive=alive)
            out = thin(x, all_spent[s] + all_budget[s])
            seq = np.full(len(g), -1)
            seq[out.removed] = np.arange(len(out.removed))
            done = g.assign(cur=x.x, alive=x.alive, seq=seq.astype(np.int32)).iloc[lo:hi]
            return done[["series_id", "chunk", "pos", "raw", "cur", "alive", "seq"]]

        tried = _cut(spread(_halo(state, chunk, reach), "series_id", "at").groupBy("series_id", "at").applyInPandas(run, STATE))
        removed = {r["series_id"]: r["k"] for r in tried.groupBy("series_id").agg(F.sum(F.when(F.col("seq") >= 0, 1).otherwise(0)).alias("k")).collect()}
        new = _sums(tried, rules, chunk)
        for _ in range(max_rollbacks):
            moved = {s: float(stats.distance(rules.distance, raw[s], _vector(new[s], rules))) for s in new}
            broken = {s for s in new if moved[s] > rules.eps}
            if not broken:
                break
            hit = df.sparkSession.sparkContext.broadcast(broken)

            def back(g: pd.DataFrame) -> pd.DataFrame:
                g = g.sort_values("pos", kind="stable")
                if g["series_id"].iloc[0] not in hit.value:
                    return g
                top = g["seq"].max()
                again = g["seq"] >= (top + 1) // 2
                g = g.assign(alive=g["alive"] | again, seq=np.where(again, -1, g["seq"]).astype(np.int32))
                level = float((g["raw"] - g["cur"])[g["alive"] & ~again].iloc[0])  # series are kept less their means
                return g.assign(cur=_redrawn(g) - level)

            tried = _cut(tried.groupBy("series_id", "chunk").applyInPandas(back, STATE))
            new = _sums(tried, rules, chunk)
            for s in broken:
                p[s] /= 2
        else:
            break
        state, sums, spent = tried, new, moved
        rounds = turn + 1
        if not any(removed.values()):
            break
    told = df.sparkSession.createDataFrame([(s, info[s][0], spent[s]) for s in sums], "series_id string, n long, deviation double")
    return state.where("alive").join(F.broadcast(told), "series_id").select("series_id", "pos", F.col("raw").alias("value"), "n", "deviation", F.lit(rounds).alias("rounds"))


def thin_bulk(df: DataFrame, rules: Rules, share: float = 0.25, max_rounds: int = 40) -> DataFrame:
    """Bulk rounds: drop many of the cheapest points that are no neighbours of each other at once, check exactly, halve the set on violation.

    Each series is one task and each round a handful of vector operations; for very many or quite long series.
    """
    from ..kernel.greedy import statistic_of

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos", kind="stable")
        x = g["value"].to_numpy(float)
        n = len(x)
        alive = np.ones(n, bool)
        base = statistic_of(x, rules)
        dist = lambda keep: float(stats.distance(rules.distance, base, statistic_of(np.interp(np.arange(n), np.nonzero(keep)[0], x[keep]), rules)))
        part, spent, rounds = share, 0.0, 0
        while n >= 3 and rounds < max_rounds and part * alive.sum() >= 1 and n / alive.sum() < rules.ratio:
            rounds += 1
            s = Series(np.interp(np.arange(n), np.nonzero(alive)[0], x[alive]), rules, alive=alive, base=base)
            live = np.nonzero(alive & ~s.fixed)[0]
            if not len(live):
                break
            order = live[np.argsort(np.round(s.impacts(live), 9), kind="stable")]
            order = order[: max(1, int(part * len(order)))]
            rank = np.full(n + 1, n + 1)
            rank[order] = np.arange(len(order))
            r_left, r_right = rank[s.left[order]], rank[np.minimum(s.right[order], n)]
            chosen = order[(rank[order] < r_left) & (rank[order] < r_right)]
            if not np.isinf(rules.ratio):
                chosen = chosen[: max(0, int(alive.sum() - np.ceil(n / rules.ratio)))]
            while len(chosen):
                keep = alive.copy()
                keep[chosen] = False
                d = dist(keep)
                if d <= rules.eps:
                    alive, spent = keep, d
                    break
                chosen = chosen[: len(chosen) // 2]
            if not len(chosen):
                part /= 4
        at = np.nonzero(alive)[0]
        return g.iloc[at][["series_id", "pos", "value"]].assign(n=n, deviation=spent, rounds=rounds)

    return df.select("series_id", "pos", "value").groupBy("series_id").applyInPandas(one, "series_id string, pos long, value double, n long, deviation double, rounds int")


__all__ = ["thin_bulk", "thin_chunked", "thin_whole"]
