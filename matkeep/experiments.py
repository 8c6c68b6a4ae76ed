"""Runs the experiments: small deletions, large deletions, break-even shares and the cost of counters, workload by workload.

Facts and materialisations are made before the clock starts, so a figure is the update alone. Every result is compared
with one built anew if ``check`` is set. ``python -m matkeep.experiments --help`` lists the options.
"""

from __future__ import annotations

import argparse
import json
from collections.abc import Iterator

from pyspark.sql import SparkSession

from .maintain import COUNTERS
from .materialise import materialise
from .measures import break_even, counter_overhead, differences, large_deletion, pick_facts, small_deletions, timed
from .programs import MUTUAL, WORKLOADS
from .store import Materialisation, settle

STRATEGIES = ("odr", "odr_2c", "pbd", "pbd_1c")
#: The predicate that facts are taken from.
CHANGED = {"cooc": "inCart", "path": "hop", "seed": "edge", "clique": "linked", "taint": "next", "copy": "markedToxic", "host": "host", "thread": "reply", "class": "ordered", "mutual": "edge"}


def prepared(spark: SparkSession, sf_dir: str, name: str, counters=(0, 1, 2)) -> tuple[object, dict, dict[int, Materialisation]]:
    """Program, explicit facts, and the materialisation with each number of counters."""
    w = WORKLOADS[name]
    if w is MUTUAL:
        batched = w.batched()
        program = batched.program
        explicit = batched.tagged(w.explicit(spark, sf_dir)) | {p: df.distinct() for p, df in batched.rule_tables(spark).items()}
    else:
        program = w.program()
        explicit = w.explicit(spark, sf_dir, program.preds)
    return program, explicit, {n: materialise(spark, program, explicit, n) for n in counters}


def speed_ups(seconds: dict[str, float]) -> dict[str, float]:
    """How many times as long each base takes as its variant with counters, and rebuilding as the fastest of all."""
    out = {}
    for base, hybrid in (("odr", "odr_2c"), ("pbd", "pbd_1c")):
        if base in seconds and hybrid in seconds:
            out[f"{base}/{hybrid}"] = seconds[base] / seconds[hybrid]
    updates = [v for s, v in seconds.items() if not s.startswith("remat")]
    if "remat" in seconds and updates:
        out["remat/best"] = seconds["remat"] / min(updates)
    return out


def exact(mats: dict[int, Materialisation], pred: str, strategy: str, n: int, seed: int) -> bool:
    """Whether the update leaves what a build without the facts gives."""
    mat = mats[COUNTERS[strategy]]
    gone = settle(pick_facts(mat.explicit[pred], n, seed))[0]
    after = timed(mat, {pred: gone}, {}, strategy)[1].mat
    anew = timed(mats[0], {pred: gone}, {}, "remat")[1].mat
    return not any(differences(after, anew).values())


def small(mats: dict[int, Materialisation], pred: str, n: int, seeds, strategies=STRATEGIES) -> dict[str, object]:
    """Best, worst and mean seconds over the seeds; ratios of the means."""
    found = small_deletions(mats, pred, (*strategies, "remat"), n, seeds)
    return {"seconds": found, "ratios": speed_ups({s: v["mean"] for s, v in found.items()})}


def large(mats: dict[int, Materialisation], pred: str, shares, strategies=STRATEGIES) -> dict[float, dict[str, float]]:
    """Seconds at each share of facts removed, rebuilding with 0, 1 and 2 counters beside them."""
    return {share: large_deletion(mats, pred, share, (*strategies, "remat", "remat_1c", "remat_2c")) for share in shares}


def experiments(spark: SparkSession, sf_dir: str, names, n: int, seeds: int, shares=(), resolution: float = 0.0, repeats: int = 0, strategies=STRATEGIES, check: bool = False) -> Iterator[dict]:
    """One record for each workload and experiment, as soon as it is done."""
    for name in names:
        program, explicit, mats = prepared(spark, sf_dir, name)
        pred = CHANGED[name]
        if n:
            yield {"workload": name, "experiment": "small", "n": n, "seeds": seeds} | small(mats, pred, n, range(seeds), strategies)
        if check:
            yield {"workload": name, "experiment": "exact", "n": n} | {s: exact(mats, pred, s, n, 0) for s in strategies}
        for share, seconds in large(mats, pred, shares, strategies).items():
            yield {"workload": name, "experiment": "large", "share": share, "seconds": seconds, "ratios": speed_ups(seconds)}
        if resolution:
            yield {"workload": name, "experiment": "break_even", "share": break_even(mats, pred, resolution=resolution, repeats=max(repeats, 1))}
        if repeats:
            yield {"workload": name, "experiment": "counter_overhead", "over": counter_overhead(spark, program, explicit, repeats)}


def main() -> None:
    args = argparse.ArgumentParser(description=__doc__)
    args.add_argument("--sf-dir", required=True)
    args.add_argument("--workloads", nargs="+", default=sorted(CHANGED), choices=sorted(CHANGED))
    args.add_argument("--strategies", nargs="+", default=STRATEGIES, choices=STRATEGIES)
    args.add_argument("--facts", type=int, default=1000, help="facts of a small deletion; 0: none")
    args.add_argument("--seeds", type=int, default=10)
    args.add_argument("--shares", type=float, nargs="*", default=())
    args.add_argument("--resolution", type=float, default=0.0, help="of the break-even share; 0: not sought")
    args.add_argument("--repeats", type=int, default=0, help="builds for the cost of counters; 0: none")
    args.add_argument("--check", action="store_true", help="compare each strategy with a build anew")
    given = args.parse_args()
    spark = SparkSession.builder.config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for record in experiments(spark, given.sf_dir, given.workloads, given.facts, given.seeds, given.shares, given.resolution, given.repeats, given.strategies, given.check):
        print(json.dumps(record), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
