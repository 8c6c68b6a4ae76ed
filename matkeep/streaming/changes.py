"""A stream of changes applied to a materialisation: netting for each fact, late rows aside, each batch once."""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..maintain import COUNTERS, Options, maintain, normalise
from ..materialise import Facts, materialise
from ..plans.firing import minus, together
from ..store import FactStore, Materialisation, settle, settle_all

#: Columns of a change log.
CHANGES = "op string, pred string, args array<string>, event_ts timestamp, change_id bigint"


def deduplicated(changes: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """Drops repeats of a change id that come within the delay."""
    return changes.withWatermark("event_ts", delay).dropDuplicatesWithinWatermark(["change_id"])


def split_late(changes: DataFrame, last_seen, delay_seconds: int) -> tuple[DataFrame, DataFrame]:
    """Changes in time, and those older than the watermark, for a dead-letter table."""
    limit = F.lit(last_seen).cast("timestamp") - F.expr(f"INTERVAL {delay_seconds} SECONDS")
    return changes.where(F.col("event_ts") >= limit), changes.where(F.col("event_ts") < limit)


def net(changes: DataFrame) -> DataFrame:
    """The last change of each fact wins: by time, then change id."""
    order = W.partitionBy("pred", "args").orderBy(F.desc("event_ts"), F.desc("change_id"))
    return changes.withColumn("_n", F.row_number().over(order)).where("_n = 1").drop("_n")


def typed(changes: DataFrame, pred: str, kinds: list[str], op: str) -> DataFrame:
    """A predicate's changes of one kind as facts of its column types."""
    args = [F.get("args", F.lit(i)).cast(k).alias(f"a{i}") for i, k in enumerate(kinds)]
    return changes.where((F.col("pred") == pred) & (F.col("op") == op)).select(*args).distinct()


class Journal:
    """Explicit facts on disk: a start, and for each applied batch its net changes of all predicates under one log entry.

    A batch counts once its entry is there; the entry is written last and never over another, so a crash before it leaves
    nothing that is read.
    """

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self._hpath = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        self._fs = self._hpath(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _write(self, name: str, entry: dict) -> None:
        stream = self._fs.create(self._hpath(f"{self.path}/_log/{name}.json"), False)
        stream.write(bytearray(json.dumps(entry).encode()))
        stream.close()

    def entries(self) -> list[dict]:
        """In the order in which they were written: by number."""
        where = self._hpath(f"{self.path}/_log")
        if not self._fs.exists(where):
            return []
        names = sorted(s.getPath().getName() for s in self._fs.listStatus(where))
        out = []
        for n in names:
            stream = self._fs.open(self._hpath(f"{self.path}/_log/{n}"))
            out.append(json.loads(self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")))
            stream.close()
        return out

    def start(self, facts: dict[str, DataFrame], types: dict[str, list[str]]) -> None:
        name = f"start-{uuid.uuid4().hex}"
        for p, df in facts.items():
            df.write.parquet(f"{self.path}/{name}/{p}")
        self._write(f"{0:012d}", {"batch": None, "types": types, "parts": {p: f"{name}/{p}" for p in facts}})

    def append(self, batch: int, removed: dict[str, DataFrame], added: dict[str, DataFrame]) -> None:
        name, parts = f"batch-{uuid.uuid4().hex}", {}
        for kind, facts in (("removed", removed), ("added", added)):
            for p, df in facts.items():
                df.write.parquet(f"{self.path}/{name}/{kind}/{p}")
                parts[f"{kind}/{p}"] = f"{name}/{kind}/{p}"
        self._write(f"{len(self.entries()):012d}", {"batch": batch, "parts": parts})

    def facts(self) -> tuple[Facts, set[int]]:
        """The explicit facts after all batches there are, and these batches."""
        entries = self.entries()
        read = lambda path: self.spark.read.parquet(f"{self.path}/{path}")
        now = {p: read(path) for p, path in entries[0]["parts"].items()}
        for e in entries[1:]:
            for kind in ("removed", "added"):
                for p, path in ((k.partition("/")[2], v) for k, v in e["parts"].items() if k.startswith(kind)):
                    now[p] = minus(now[p], read(path)) if kind == "removed" else together(now.get(p), read(path))
        return Facts(settle_all(now)[0], entries[0]["types"]), {e["batch"] for e in entries[1:]}


class Keeper:
    """Holds a materialisation and applies netted micro-batches to it, each batch id once.

    With a journal the batches outlive the process: ``reopen`` builds the materialisation from it, and a batch that a
    restarted stream replays is known. Changes of predicates the program's facts do not have, or with the wrong number of
    arguments or arguments of the wrong type, are added to ``dead_letters``, which is a path or None.
    """

    def __init__(self, mat: Materialisation, strategy: str = "odr_2c", options: Options = Options(), stores: dict[str, FactStore] | None = None, journal: Journal | None = None, dead_letters: str | None = None):
        self.mat, self.strategy, self.options, self.stores, self.journal, self.dead_letters = mat, strategy, options, stores or {}, journal, dead_letters
        self.done: set[int] = set()
        if journal is not None:
            if journal.entries():
                self.done = journal.facts()[1]
            else:
                journal.start(mat.explicit, mat.types)

    @classmethod
    def reopen(cls, spark: SparkSession, program, journal: Journal, strategy: str = "odr_2c", **more) -> Keeper:
        facts, _ = journal.facts()
        return cls(materialise(spark, program, facts, COUNTERS[strategy]), strategy, journal=journal, **more)

    def apply(self, batch: DataFrame, batch_id: int) -> bool:
        """False if this batch was applied before."""
        if batch_id in self.done:
            return False
        changes, _ = settle(net(batch))
        types = self.mat.types
        if self.dead_letters is not None:
            self._usable(changes, types, False).write.mode("append").parquet(self.dead_letters)
        changes = self._usable(changes, types, True)
        named = [r[0] for r in changes.select("pred").distinct().collect()]  # no more than the program's predicates
        removed, added = ({p: typed(changes, p, types[p], op) for p in named} for op in "-+")
        removed, added = normalise(self.mat.explicit, removed, added)
        report = maintain(self.mat, removed, added, self.strategy, self.options)
        for p, store in self.stores.items():
            store.apply(batch_id, report.deleted.get(p), report.added.get(p))
        if self.journal is not None:
            self.journal.append(batch_id, removed, added)
        self.mat = report.mat
        self.done.add(batch_id)
        return True

    def _usable(self, changes: DataFrame, types: dict[str, list[str]], good: bool) -> DataFrame:
        fits = F.lit(False)
        for p, kinds in types.items():
            args = [F.get("args", F.lit(i)).try_cast(k).isNotNull() for i, k in enumerate(kinds)]
            fits = fits | ((F.col("pred") == p) & (F.size("args") == len(kinds)) & reduce(lambda x, y: x & y, args, F.lit(True)))
        fits = F.coalesce(fits & F.col("op").isin("-", "+"), F.lit(False))
        return changes.where(fits if good else ~fits)

    def attach(self, stream: DataFrame, checkpoint: str, before: Callable[[DataFrame], DataFrame] = lambda df: df):
        """Starts a query that applies every micro-batch there is and then stops."""
        return (
            before(stream)
            .writeStream.foreachBatch(lambda df, n: self.apply(df, n) and None)
            .option("checkpointLocation", checkpoint)
            .trigger(availableNow=True)
            .start()
        )


def with_details(changes: DataFrame, details: DataFrame) -> DataFrame:
    """A stream of changes with columns of a static table, by its columns pred and fact (the arguments as JSON)."""
    return changes.withColumn("fact", F.to_json("args")).join(details, ["pred", "fact"], "left")


def taken_back(changes: DataFrame, delay: str = "10 minutes", within: str = "5 minutes") -> DataFrame:
    """Insertions whose deletion follows in the stream within an interval: a join of the stream with itself.

    pred, fact, inserted, deleted. Both sides have a watermark and the join a time bound, so state is dropped in time.
    """
    side = lambda op, name: (
        changes.withWatermark("event_ts", delay).where(F.col("op") == op).select(F.col("pred").alias(f"{name}_pred"), F.to_json("args").alias(f"{name}_fact"), F.col("event_ts").alias(name))
    )
    put, gone = side("+", "inserted"), side("-", "deleted")
    same = (F.col("inserted_pred") == F.col("deleted_pred")) & (F.col("inserted_fact") == F.col("deleted_fact"))
    soon = (F.col("deleted") >= F.col("inserted")) & (F.col("deleted") <= F.col("inserted") + F.expr(f"INTERVAL {within}"))
    return put.join(gone, same & soon).select(F.col("inserted_pred").alias("pred"), F.col("inserted_fact").alias("fact"), "inserted", "deleted")


def last_change_state(changes: DataFrame) -> DataFrame:
    """The last change of each fact as a stateful stream operator; state is one row for each fact.

    pred, fact (the arguments as JSON, so that no two facts have one name), op, change_id.
    """
    import pandas as pd

    def keep(key, batches, state):
        best = tuple(state.get) if state.exists else None
        for pdf in batches:
            row = pdf.sort_values(["event_ts", "change_id"]).iloc[-1]
            now = (row["op"], int(row["change_id"]), row["event_ts"].value // 1000)
            if best is None or (now[2], now[1]) > (best[2], best[1]):
                best = now
        if best is not None:
            state.update(best)
            yield pd.DataFrame({"pred": [key[0]], "fact": [key[1]], "op": [best[0]], "change_id": [best[1]]})

    keyed = changes.withColumn("fact", F.to_json("args")).select("pred", "fact", "op", "change_id", "event_ts")
    return keyed.groupBy("pred", "fact").applyInPandasWithState(
        keep, "pred string, fact string, op string, change_id long", "op string, change_id long, ts long", "update", "NoTimeout"
    )
