"""Measures over updates: times over random subsets, large deletions, break-even, counter overhead, work, accuracy."""

from __future__ import annotations

import statistics
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .maintain import COUNTERS, Options, maintain
from .materialise import materialise
from .plans.firing import columns_of
from .store import Materialisation, settle


def hash_order(df: DataFrame, seed: int):
    """A repeatable random order of facts that other engines can compute too."""
    key = F.concat_ws("/", *[F.col(c).cast("string") for c in columns_of(df)])
    return F.md5(F.concat(key, F.lit(f"/{seed}")))


def pick_facts(df: DataFrame, n: int, seed: int) -> DataFrame:
    """The first n facts in hash order."""
    return df.orderBy(hash_order(df, seed), *columns_of(df)).limit(n)


def pick_fraction(df: DataFrame, share: float, seed: int) -> DataFrame:
    """A share of the facts by hash; larger shares hold smaller ones."""
    top = int(share * (1 << 32))
    return df.where(F.conv(F.substring(hash_order(df, seed), 1, 8), 16, 10).cast("bigint") < top)


def timed(mat: Materialisation, removed: dict, added: dict, strategy: str, options: Options = Options()) -> tuple[float, object]:
    """Seconds of an update with its result run, and the report."""
    began = time.time()
    report = maintain(mat, removed, added, strategy, options)
    for df in report.mat.facts.values():
        df.write.format("noop").mode("overwrite").save()
    return time.time() - began, report


def small_deletions(mats: dict[int, Materialisation], pred: str, strategies, n: int = 1000, seeds=range(10)) -> dict[str, dict[str, float]]:
    """Best, worst and mean seconds of deleting n random facts, for each strategy."""
    out = {}
    for s in strategies:
        mat = mats[COUNTERS[s]]
        times = [timed(mat, {pred: settle(pick_facts(mat.explicit[pred], n, seed))[0]}, {}, s)[0] for seed in seeds]
        out[s] = {"best": min(times), "worst": max(times), "mean": statistics.mean(times)}
    return out


def large_deletion(mats: dict[int, Materialisation], pred: str, share: float, strategies, seed: int = 0) -> dict[str, float]:
    out = {}
    for s in strategies:
        mat = mats[COUNTERS[s]]
        gone = settle(pick_fraction(mat.explicit[pred], share, seed))[0]
        out[s] = timed(mat, {pred: gone}, {}, s)[0]
    return out


def break_even(mats: dict[int, Materialisation], pred: str, hybrids=("odr_2c", "pbd_1c"), resolution: float = 0.01, tolerance: float = 1.1, repeats: int = 3) -> float:
    """The largest share of facts whose deletion costs the better hybrid no more than rebuilding, by bisection."""

    def pays(share: float) -> bool:
        runs = [large_deletion(mats, pred, share, (*hybrids, "remat")) for _ in range(repeats)]
        median = {s: statistics.median(r[s] for r in runs) for s in runs[0]}
        return min(median[h] for h in hybrids) <= tolerance * median["remat"]

    low, high = 0.0, 1.0
    while high - low > resolution:
        mid = (low + high) / 2
        low, high = (mid, high) if pays(mid) else (low, mid)
    return low


def counter_overhead(spark: SparkSession, program, explicit: dict, repeats: int = 3) -> dict[int, float]:
    """Seconds of building with 1 and 2 counters over building with none, minus one."""
    times = {}
    for n in (0, 1, 2):
        runs = []
        for _ in range(repeats):
            began = time.time()
            materialise(spark, program, explicit, n)
            runs.append(time.time() - began)
        times[n] = statistics.median(runs)
    return {n: times[n] / times[0] - 1 for n in (1, 2)}


def differences(a: Materialisation, b: Materialisation) -> dict[str, int]:
    """How many facts of each predicate only one of two materialisations has; all zero if they agree."""
    out = {}
    for p in set(a.facts) | set(b.facts):
        x, y = a.of(p), b.of(p)
        if x is None or y is None:
            out[p] = (x if y is None else y).count()
        else:
            y = y.select(*x.columns)
            out[p] = x.exceptAll(y).count() + y.exceptAll(x).count()
    return out
