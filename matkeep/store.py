"""Stored facts: lineage cuts in the shared folder, materialisations, snapshots with overlays, compaction, commit log."""

from __future__ import annotations

import json
import tempfile
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from .plans.firing import Bag, columns_of, meet, minus, together
from .strata import Stratification


def shared_dir(spark: SparkSession) -> str:
    """The folder the session names in ``spark.checkpoint.dir``; a temporary one is set only where it names none."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        master = spark.sparkContext.master
        if not master.startswith("local") or "cluster" in master:
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        named = tempfile.mkdtemp(prefix="matkeep-")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def settle(df: DataFrame) -> tuple[DataFrame, int]:
    """Runs the plan once: its rows are written to the shared folder and counted on the way.

    One job, no second pass for the count, and what follows reads files that outlive any executor.
    """
    path = f"{shared_dir(df.sparkSession)}/settled-{uuid.uuid4().hex}"
    seen = Observation()
    df.observe(seen, F.count(F.lit(1)).alias("n")).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), seen.get["n"]


#: Frames of one step that are written at the same time.
AT_ONCE = 4


def _each(make, frames: dict[str, DataFrame]) -> dict:
    """``make`` of each frame; the jobs of several frames are submitted together."""
    if len(frames) < 2:
        return {p: make(df) for p, df in frames.items()}
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return dict(zip(frames, pool.map(make, frames.values()), strict=True))


def settle_bag(bag: Bag) -> tuple[Bag, int, int]:
    """Settles the frames of a bag; also how many heads there are and how many instances they stand for."""

    def one(df: DataFrame) -> tuple[DataFrame, int, int]:
        path, seen = f"{shared_dir(df.sparkSession)}/settled-{uuid.uuid4().hex}", Observation()
        df.observe(seen, F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("m"), F.lit(0)).alias("m")).write.parquet(path)
        return df.sparkSession.read.schema(df.schema).parquet(path), seen.get["n"], seen.get["m"]

    done = _each(one, bag)
    return {p: df for p, (df, n, _) in done.items() if n}, sum(n for _, n, _ in done.values()), sum(m for _, _, m in done.values())


def settle_all(frames: dict[str, DataFrame]) -> tuple[dict[str, DataFrame], dict[str, int]]:
    """Settles several frames; empty ones are left out of the first result."""
    done = _each(settle, frames)
    return {p: df for p, (df, n) in done.items() if n}, {p: n for p, (_, n) in done.items()}


def mark(df: DataFrame, known: DataFrame | None, name: str) -> DataFrame:
    """The rows with one column more: whether the row's fact is in the set, which has each fact once."""
    cols = columns_of(df)
    if known is None or not cols:
        return df.withColumn(name, F.lit(known is not None and not known.isEmpty()))
    return df.join(known.select(*cols, F.lit(True).alias(name)), cols, "left").withColumn(name, F.coalesce(name, F.lit(False)))


#: Beyond so many rows the flagged ones of a frame are written apart if they are less than half of it, so that later
#: steps read no more than these; below, one job is cheaper than the reading.
APART = 50_000


def settle_flagged(df: DataFrame, flag: str) -> tuple[DataFrame, int, int, int]:
    """Settles a frame with a boolean column; also how many rows it has, how many are flagged, and the sum of ``m``."""
    path, seen = f"{shared_dir(df.sparkSession)}/settled-{uuid.uuid4().hex}", Observation()
    m = F.coalesce(F.sum("m" if "m" in df.columns else F.lit(0)), F.lit(0))
    df.observe(seen, F.count(F.lit(1)).alias("n"), F.count_if(F.col(flag)).alias("yes"), m.alias("m")).write.parquet(path)
    got = seen.get
    return df.sparkSession.read.schema(df.schema).parquet(path), got["n"], got["yes"], got["m"]


def settle_marked(frames: Bag) -> tuple[Bag, dict[str, DataFrame], int, int]:
    """Settles bags with a column ``fresh`` in one job each: the bags, their fresh facts, how many heads and instances."""

    def one(df: DataFrame) -> tuple[DataFrame, DataFrame | None, int, int]:
        kept, n, yes, m = settle_flagged(df, "fresh")
        fresh = kept.where("fresh").select(*columns_of(kept)) if yes else None
        if yes and n > APART and 2 * yes < n:
            fresh = settle(fresh)[0]
        return kept.drop("fresh"), fresh, n, m

    done = _each(one, frames)
    bag = {p: df for p, (df, _, n, _) in done.items() if n}
    return bag, {p: df for p, (_, df, _, _) in done.items() if df is not None}, sum(d[2] for d in done.values()), sum(d[3] for d in done.values())


#: Bytes from which on a set that every step of a loop joins is kept by the keys of that join.
ARRANGED = 64 << 20


def size_of(df: DataFrame) -> int:
    """Bytes as the optimizer knows them, of files as they are; no job."""
    return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())


def arranged(df: DataFrame, cols: list[str]) -> DataFrame:
    """The rows dealt and sorted by these columns, kept on the executors' disks until they are let go: joins by them
    neither move nor sort these rows again. A lost part is made anew from the files the frame reads."""
    dealt = df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *cols)
    kept = dealt.sortWithinPartitions(*cols).persist(StorageLevel.DISK_ONLY)
    kept.count()  # how the rows lie is known to later plans only once they are there
    return kept


#: Parts that are merged at a time.
MERGED = 4


class Growing(dict):
    """Fact sets that grow by disjoint parts. Four parts merged equally often are merged, so that there are few of them,
    few steps write one, and no fact is written more often than the logarithm of the number of parts. What a set starts
    with is never rewritten."""

    def __init__(self, start: dict[str, DataFrame] | None = None):
        super().__init__(start or {})
        self._base = dict(self)
        self._parts: dict[str, list[tuple[int, DataFrame]]] = {}

    def grow(self, more: dict[str, DataFrame]) -> None:
        for p, df in more.items():
            parts = self._parts.setdefault(p, [])
            parts.append((0, df))
            while len(parts) >= MERGED and parts[-1][0] == parts[-MERGED][0]:
                level, same = parts[-1][0], parts[-MERGED:]
                del parts[-MERGED:]
                parts.append((level + 1, settle(together(*[d for _, d in same]))[0]))
            self[p] = together(self._base.get(p), *[d for _, d in parts])


@dataclass
class Layers:
    """A stored set and its net change since: two small settled frames, whatever the number of updates.

    ``base`` is written anew once the change has grown to a share of it.
    """

    #: Share of the base from which the change is folded into it.
    FOLD = 0.25

    base: DataFrame
    size: int
    less: DataFrame | None = None
    more: DataFrame | None = None

    def now(self) -> DataFrame:
        return together(minus(self.base, self.less), self.more)

    def changed(self, lost: DataFrame | None, gained: DataFrame | None, whole: bool = True) -> Layers:
        """``lost`` is within the set, ``gained`` apart from it. ``whole``: a row is its key, so a row of the base that
        comes back is the same row; rows with counters are not."""
        less, more = self.less, self.more
        if lost is not None:
            deeper = lost if more is None else minus(lost, more)
            less, more = together(less, deeper), None if more is None else minus(more, lost)
        if gained is not None:
            again = None if less is None or not whole else meet(gained, less)
            less, more = less if again is None else minus(less, gained), together(more, gained if again is None else minus(gained, again))
        kept, sizes = settle_all({k: df for k, df in (("less", less), ("more", more)) if df is not None})
        out = Layers(self.base, self.size, kept.get("less"), kept.get("more"))
        if sum(sizes.values()) > self.FOLD * self.size:
            out = Layers(*settle(out.now()))
        return out


@dataclass
class Materialisation:
    """Explicit facts, all facts, and counters (a0.., c_nr, c_r) of every derived predicate."""

    spark: SparkSession
    strat: Stratification
    explicit: dict[str, DataFrame]
    facts: dict[str, DataFrame]
    counters: dict[str, DataFrame] = field(default_factory=dict)
    #: Column types of every explicit predicate, those without facts included.
    types: dict[str, list[str]] = field(default_factory=dict)
    layers: dict[tuple[str, str], Layers] = field(default_factory=dict)
    #: The classes of symmetric and transitive predicates (``classes.Classes``); their facts and counters follow from these.
    classes: dict[str, object] = field(default_factory=dict)

    def of(self, pred: str) -> DataFrame | None:
        return self.facts.get(pred)

    def sql(self, text: str) -> DataFrame:
        """A goal query: every predicate is a view of its name."""
        for p, df in self.facts.items():
            df.createOrReplaceTempView(p)
        return self.spark.sql(text)


def add_counts(parts: list[tuple[Bag, int, int]]) -> dict[str, DataFrame]:
    """Sums bags into counters: each part is (bag, weight for c_nr, weight for c_r), or as ``fold_counts`` makes it."""
    by_pred: dict[str, list[DataFrame]] = {}
    for bag, nr, r in parts:
        for p, df in bag.items():
            cols = columns_of(df)
            if nr is None:
                by_pred.setdefault(p, []).append(df.select(*cols, "c_nr", "c_r"))
                continue
            by_pred.setdefault(p, []).append(df.select(*cols, (F.col("m") * nr).cast("bigint").alias("c_nr"), (F.col("m") * r).cast("bigint").alias("c_r")))
    out = {}
    for p, dfs in by_pred.items():
        both = dfs[0]
        for d in dfs[1:]:
            both = both.unionByName(d)
        out[p] = both.groupBy(*columns_of(both)).agg(F.sum("c_nr").alias("c_nr"), F.sum("c_r").alias("c_r"))
    return out


def fold_counts(parts: list, most: int = 8) -> list:
    """The same sums in fewer parts once there are more than ``most``: a long loop keeps short plans.

    A folded part is a bag whose frames have c_nr and c_r in place of m.
    """
    return parts if len(parts) <= most else [(settle_all(add_counts(parts))[0], None, None)]


class FactStore:
    """Snapshots of one predicate's facts on disk, by bucket of a layout argument.

    ``base`` holds facts under ``bucket=``; each update appends an overlay of signed rows (``d`` +1 or -1), named in a
    commit log under its batch id. A batch id is committed once, so a replayed batch changes nothing. Reading adds the
    overlays to the base; compaction rewrites only buckets an overlay has touched.
    """

    def __init__(self, spark: SparkSession, path: str, buckets: int = 16, layout: str = "a0"):
        self.spark, self.path, self.buckets, self.layout = spark, path.rstrip("/"), buckets, layout
        jvm = spark.sparkContext._jvm
        self._hpath = jvm.org.apache.hadoop.fs.Path
        self._fs = self._hpath(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _bucketed(self, df: DataFrame) -> DataFrame:
        return df.withColumn("bucket", F.pmod(F.xxhash64(self.layout), F.lit(self.buckets)).cast("int"))

    def log(self) -> list[dict]:
        where = self._hpath(f"{self.path}/_log")
        if not self._fs.exists(where):
            return []
        names = sorted(s.getPath().getName() for s in self._fs.listStatus(where))
        return [self._entry(n) for n in names if n.endswith(".json")]

    def _entry(self, name: str) -> dict:
        """Read by the file system: an entry is one line, no job."""
        stream = self._fs.open(self._hpath(f"{self.path}/_log/{name}"))
        try:
            return json.loads(self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def _commit(self, entry: dict) -> None:
        at = self._hpath(f"{self.path}/_log/{entry['version']:012d}.json")
        stream = self._fs.create(at, False)  # fails if another writer has this version
        stream.write(bytearray(json.dumps(entry).encode()))
        stream.close()

    def create(self, df: DataFrame) -> None:
        name = f"base-{uuid.uuid4().hex}"
        self._bucketed(df).repartition("bucket").write.partitionBy("bucket").parquet(f"{self.path}/{name}")
        self._commit({"version": 0, "batch": None, "base": [[name, None]], "overlays": []})

    def state(self) -> dict:
        return self.log()[-1]

    def apply(self, batch: int, minus: DataFrame | None, plus: DataFrame | None) -> bool:
        """Appends an overlay; false if this batch is in the log already."""
        entries = self.log()
        if any(e["batch"] == batch for e in entries):
            return False
        now = entries[-1]
        parts = [df.withColumn("d", F.lit(d).cast("int")) for df, d in ((minus, -1), (plus, 1)) if df is not None]
        overlay = now["overlays"]
        if parts:
            name = f"overlay-{uuid.uuid4().hex}"
            both = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
            self._bucketed(both).write.partitionBy("bucket").parquet(f"{self.path}/{name}")
            overlay = [*overlay, name]
        self._commit({"version": now["version"] + 1, "batch": batch, "base": now["base"], "overlays": overlay})
        return True

    def read(self, touched: DataFrame | None = None) -> DataFrame:
        """The facts now. ``touched`` (with the layout column) limits the scan to the buckets it falls in."""
        now = self.state()
        only = None
        if touched is not None:  # at most ``buckets`` numbers
            only = [r[0] for r in self._bucketed(touched.select(self.layout)).select("bucket").distinct().collect()]
        keep = lambda df: df if only is None else df.where(F.col("bucket").isin(only))
        base = None
        for name, ids in now["base"]:
            part = keep(self.spark.read.parquet(f"{self.path}/{name}"))
            part = part if ids is None else part.where(F.col("bucket").isin(ids))
            base = part if base is None else base.unionByName(part)
        for name in now["overlays"]:
            change = keep(self.spark.read.parquet(f"{self.path}/{name}"))
            cols = columns_of(base)
            base = base.join(change.where("d < 0"), [*cols, "bucket"], "left_anti")
            base = base.unionByName(change.where("d > 0").drop("d"))
        return base.drop("bucket")

    def compact(self) -> int:
        """Folds the overlays into new files of the buckets they touch; returns how many buckets that were."""
        now = self.state()
        if not now["overlays"]:
            return 0
        touched = sorted({r[0] for n in now["overlays"] for r in self.spark.read.parquet(f"{self.path}/{n}").select("bucket").distinct().collect()})
        rows = self._bucketed(self.read()).where(F.col("bucket").isin(touched))
        name = f"base-{uuid.uuid4().hex}"
        rows.repartition("bucket").write.partitionBy("bucket").parquet(f"{self.path}/{name}")
        every = set(range(self.buckets))
        old = [[n, sorted((set(ids) if ids is not None else every) - set(touched))] for n, ids in now["base"]]
        base = [[n, ids] for n, ids in old if ids] + [[name, touched]]
        self._commit({"version": now["version"] + 1, "batch": None, "base": base, "overlays": []})
        return len(touched)
