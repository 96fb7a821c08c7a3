"""Balanced parallel sorts: deterministic, randomised and iterated oversampling over tagged runs."""

from __future__ import annotations

import contextlib
import time
import warnings
from collections.abc import Iterator
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evenlane.functions.spec import Key, SortSpec
from evenlane.operators import networks, prefix, sampling
from evenlane.operators.fences import FenceSet, group_fences, pick, ranked_sample
from evenlane.operators.layout import Lanes, Run, by_number, indexed, partitions, sorted_run, starts
from evenlane.operators.split import count_matrix, with_bucket
from evenlane.plans import advisor, bounds
from evenlane.plans.model import MACHINES, MachineModel
from evenlane.staging import stage

#: Samples up to this many rows are sorted by one small window; larger ones by the engine's own distributed sort.
SMALL_SAMPLE = 2_000_000


def exchanges(df: DataFrame) -> int:
    """Exchanges of rows in df's plan; those inside subqueries and cached or staged inputs are not df's own."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return sum(1 for line in plan.split("Subqueries")[0].splitlines() if " Exchange " in f" {line.lstrip(' :+-*()0123456789')}")


@dataclass
class SortResult:
    """What a sort made: the run with its buckets, the fences, and what is derived from them."""

    run: Run
    fences: FenceSet
    split: DataFrame  # the run's rows with bucket
    plan: dict
    phases: dict[str, float] = field(default_factory=dict)
    tagged: bool = True
    place: str = "pos"  # a column that the rows carry to their buckets besides; pos orders a lane's rows of one key

    @property
    def spec(self) -> SortSpec:
        return self.run.spec

    @property
    def p(self) -> int:
        return self.run.lanes.p

    @property
    def rounds(self) -> int:
        """Exchanges of all rows from their first lanes to their buckets, as the plans have them."""
        return self.run.moves + exchanges(self.routed)

    @property
    def counts(self) -> DataFrame:
        """Rows (bucket, lane, cnt)."""
        return count_matrix(self.split)

    def sizes(self) -> DataFrame:
        """Rows (bucket, size), empty buckets included."""
        spark = self.split.sparkSession
        have = self.split.groupBy("bucket").agg(F.count("*").alias("size"))
        return spark.range(self.p).select(F.col("id").cast("int").alias("bucket")).join(have, "bucket", "left").select("bucket", F.coalesce("size", F.lit(0)).cast("long").alias("size"))

    def bucket_sizes(self) -> list[int]:
        size = {r["bucket"]: r["size"] for r in self.split.groupBy("bucket").agg(F.count("*").alias("size")).collect()}  # one a bucket
        return [size.get(i, 0) for i in range(self.p)]

    def offsets(self) -> DataFrame:
        return prefix.window_offsets(self.counts)

    @property
    def routed(self) -> DataFrame:
        """The one bulk exchange: rows in the partition of their bucket, blocks of the runs in it."""
        return self.split.repartitionById(self.p, "bucket")

    @property
    def df(self) -> DataFrame:
        """The sorted table: partition b holds bucket b in order of (keys, lane, pos)."""
        return self.routed.sortWithinPartitions(*self.order)

    @property
    def by_keys(self) -> DataFrame:
        """The sorted table without tags: they choose a row's bucket and stay behind, so that keys alone are moved and compared.

        Equal keys come in any order. A single key of fixed width is sorted by radix where the session allows.
        """
        return self.split.drop("lane", "pos").repartitionById(self.p, "bucket").sortWithinPartitions(*self.spec.order())

    @property
    def order(self) -> list[Column]:
        return self.spec.order("lane", *dict.fromkeys(("pos", self.place)))

    @property
    def windowed(self) -> DataFrame:
        """The sorted table ordered for windows over buckets, which then take no exchange of their own."""
        return self.routed.sortWithinPartitions("bucket", *self.order)

    def with_rank(self, name: str = "rank") -> DataFrame:
        """The sorted table with its 1-based position: the bucket's start plus the local index."""
        sizes = self.bucket_sizes()
        base = starts(list(enumerate(sizes)), self.p)
        at = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
        return self.df.withColumn(name, by_number(base, F.col("bucket")) + at + 1)


def sort_sample(sample: DataFrame, run: Run, how: str, s: int) -> DataFrame:
    """The sample ranked: by the driver's window, Spark's distributed sort, a network, or the method itself, whose own sample is small."""
    p, spec = run.lanes.p, run.spec
    if how == "driver" and s * p <= SMALL_SAMPLE:
        return ranked_sample(sample, spec)
    if how in ("bitonic", "odd_even"):
        schedule = networks.bitonic_schedule(p) if how == "bitonic" else networks.odd_even_schedule(p)
        return networks.network_sort(sample, spec, p, schedule)
    if how == "recursive":
        t = stage(sample, "sample")
        keyed = SortSpec((Key("pad"), *[Key(n, k.asc, k.nulls_first) for n, k in zip(spec.names, spec.keys, strict=True)], Key("lane"), Key("pos"), Key("j")))
        inner = regular_sort(t, keyed, Lanes(p, layout="inplace"), dup=False).with_rank("rank")
        return inner.select("rank", "pad", "j", *[F.col(f"k{i + 1}").alias(n) for i, n in enumerate(spec.names)], F.col(f"k{len(spec.keys) + 1}").alias("lane"), F.col(f"k{len(spec.keys) + 2}").alias("pos"))
    if how in ("spark", "driver"):
        t, counts = indexed(sample.repartitionByRange(max(1, p), "pad", *spec.order("lane", "pos")).sortWithinPartitions("pad", *spec.order("lane", "pos", "j")), "sample")
        rows = [(r["__part"], r["rows"]) for r in counts.collect()]
        base = starts(rows, max([r[0] for r in rows], default=0) + 1)
        return t.withColumn("rank", by_number(base, F.col("__part")) + F.col("__at") + 1).drop("__part", "__at")
    raise ValueError(f"unknown sample sort {how}")


def lane_fences(run: Run, s: int | None, how: str, seed: int = 42, presort: bool = True) -> FenceSet:
    """p - 1 fences from samples of the run's partitions as they lie."""
    sample = sampling.sample_lanes(run, s, how, seed, presort)
    if run.total and run.total // SMALL_SAMPLE >= sampling.SHARE:  # the sample may be too large for one window
        total = sample.count()
        if total > SMALL_SAMPLE:
            return pick(sort_sample(sample.withColumns({"pad": F.lit(0), "j": F.lit(0)}), run, "spark", total), run.spec, run.lanes.p)
    found = group_fences(sample, run.spec, run.lanes.p).get(0, {})
    return FenceSet(run.spec, tuple(found[i] for i in sorted(found)))


def _timed(phases: dict[str, float], name: str, since: float) -> float:
    now = time.perf_counter()
    phases[name] = phases.get(name, 0.0) + now - since
    return now


@contextlib.contextmanager
def local_sort(spark: SparkSession, local: str) -> Iterator[None]:
    """Spark's radix sort of single fixed-width keys on or off for what runs inside."""
    if local not in ("radix", "cmp"):
        raise ValueError(f"unknown local sort {local}")
    name = "spark.sql.sort.enableRadixSort"
    old = spark.conf.get(name)
    spark.conf.set(name, "true" if local == "radix" else "false")
    try:
        yield
    finally:
        spark.conf.set(name, old)


def regular_sort(
    df: DataFrame, spec: SortSpec, lanes: Lanes, r: int | None = None, split: str = "tree", sample_sort: str = "driver", dup: bool = True, spacing: str = "even", local: str = "radix"
) -> SortResult:
    """Deterministic oversampling: sorted runs, s = r p regular samples a lane, fences, one exchange, stable merge.

    No bucket is larger than (s + p - 1) x, x the segment length, whatever the keys: repeated keys are told
    apart by (lane, pos), which only samples and fences carry. dup=False compares keys alone. Empty and
    short inputs give empty buckets. In place, one job counts the input's partitions and one samples their sorted keys; each
    sample stands for equally many rows, and r is 6, the method's ratio for fewer than 2^64 rows.
    """
    with local_sort(df.sparkSession, local):
        t = time.perf_counter()
        run = sorted_run(df, spec, lanes)
        phases: dict[str, float] = {}
        _timed(phases, "local sort", t)
        return regular_from(run, r, split, sample_sort, dup, spacing, phases)


def regular_from(run: Run, r: int | None = None, split: str = "tree", sample_sort: str = "driver", dup: bool = True, spacing: str = "even", phases: dict[str, float] | None = None) -> SortResult:
    """The deterministic method from a run on."""
    phases = {} if phases is None else phases
    t = time.perf_counter()
    p, spec = run.lanes.p, run.spec
    r = r or (6 if run.inplace else sampling.regular_ratio(run.n, p))
    if r < 1:
        raise ValueError("the oversampling ratio must be at least 1")
    s = r * p
    if p == 1:
        fences, count = FenceSet(spec, ()), p
    elif run.inplace:
        fences = lane_fences(run, s, "regular")
        count = len(run.lengths)
    else:
        sample, count = sampling.sample_regular(run, s, spacing), p
        whole = len(run.lengths) == p and (spacing == "padded" or all(run.lengths))
        fences = pick(sort_sample(sample, run, sample_sort, s), spec, p, s if whole else None) if run.n else FenceSet(spec, ())
    if p > 1:
        for w in bounds.regular_conditions(run.n, p, r, count):
            warnings.warn(w, stacklevel=3)
    _timed(phases, "sampling", t)
    plan = {"method": "regular", "p": p, "r": r, "s": s, "spacing": spacing, "split": split, "sample_sort": sample_sort, "dup": dup}
    return SortResult(run, fences, with_bucket(run.df, fences, split, dup), plan, phases, dup)


def local_run(df: DataFrame, spec: SortSpec, lanes: Lanes, local: str, presort: bool = True) -> Run:
    """The run, with Spark's radix sort of key prefixes on or off while it is written."""
    with local_sort(df.sparkSession, local):
        return sorted_run(df, spec, lanes, presort)


def presorted_random_sort(
    df: DataFrame, spec: SortSpec, lanes: Lanes, s: int | None = None, mode: str = "exact", seed: int = 42, split: str = "tree", sample_sort: str = "driver", dup: bool = True, local: str = "radix"
) -> SortResult:
    """The deterministic sort's skeleton with s random samples of each lane's sorted run."""
    with local_sort(df.sparkSession, local):
        phases: dict[str, float] = {}
        t = time.perf_counter()
        run = sorted_run(df, spec, lanes)
        t = _timed(phases, "local sort", t)
        s = s or (None if run.inplace else sampling.random_size(run.n))
        fences = random_fences(run, s, mode, seed, sample_sort)
        _timed(phases, "sampling", t)
    plan = {"method": "presorted_random", "p": lanes.p, "s": s, "mode": mode, "seed": seed, "split": split, "sample_sort": sample_sort, "dup": dup}
    return SortResult(run, fences, with_bucket(run.df, fences, split, dup), plan, phases, dup)


def random_fences(run: Run, s: int | None, mode: str, seed: int, sample_sort: str = "driver", presort: bool = True) -> FenceSet:
    p = run.lanes.p
    if p == 1:
        return FenceSet(run.spec, ())
    if run.inplace:
        return lane_fences(run, s, "random", seed, presort)
    if not run.n:
        return FenceSet(run.spec, ())
    sample = sampling.sample_random(run, s, mode, seed)
    whole = mode == "exact" and len(run.lengths) == p and min(run.lengths) >= s
    return pick(sort_sample(sample, run, sample_sort, s), run.spec, p, s if whole else None)


def classic_random_sort(df: DataFrame, spec: SortSpec, lanes: Lanes, s: int | None = None, seed: int = 42, dup: bool = True, split: str = "tree") -> SortResult:
    """Traditional sample sort: rows are sampled and routed unsorted, each by its own search among the fences, and sorted after.

    A row's address is its input position in its lane. split="integer" forms the buckets in each lane first.
    """
    run = sorted_run(df, spec, lanes, presort=False)
    s = s or (None if run.inplace else sampling.random_size(run.n))
    fences = random_fences(run, s, "exact", seed, presort=False)
    rows = with_bucket(run.df, fences, "tree", dup)
    out = SortResult(run, fences, rows, {"method": "classic_random", "p": lanes.p, "s": s, "seed": seed, "dup": dup, "split": split}, tagged=dup)
    if split == "integer":
        out.split, out.place = formed_buckets(rows), "seat"
    return out


def formed_buckets(split: DataFrame) -> DataFrame:
    """Each task's rows in blocks, one a bucket in input order, by a sort on the small integer alone; seat is the place after it.

    A lane too large for one task is read in pieces, each with seats of its own: they order no rows across pieces, pos does.
    """
    return split.sortWithinPartitions("bucket", "lane", "pos").withColumn("seat", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))


def iterated_sort(df: DataFrame, spec: SortSpec, lanes: Lanes, k: int, rounds: int, r: int = 4, method: str = "regular", seed: int = 42) -> SortResult:
    """p = k^rounds buckets in rounds of k, each of which moves all rows: for p beyond what one round's sample and blocks allow.

    A round samples every lane, finds k - 1 fences for each group of lanes in one pass over all samples, and sends
    a lane's k blocks to one lane each of their new groups, so a lane writes k blocks and not p. Moved rows are written to a table;
    the last round's exchange is the result's. Rows keep their first tags, so order and stability are those of one round.
    """
    p = lanes.p
    if k**rounds != p:
        raise ValueError("p must be k to the number of rounds")
    first = run = sorted_run(df, spec, lanes)
    cur = run.df.withColumn("group", F.lit(0))
    known: dict[int, dict] = {}  # bucket of this level -> the fence it lies above
    s = r * k if method == "regular" else None
    for level in range(rounds):
        part = Run(cur, spec, lanes, moves=level)
        found = group_fences(sampling.sample_lanes(part, s, method, seed + level, group="group"), spec, k)
        first.total = part.total
        known = {b * k: f for b, f in known.items()} | {g * k + i: f for g, fences in found.items() for i, f in fences.items()}
        names = sorted(known)
        fences = FenceSet(spec, tuple(known[b] for b in names), (0, *names))
        cur = with_bucket(cur.drop("group"), fences).withColumnRenamed("bucket", "group")
        if level < rounds - 1:
            width = p // k ** (level + 1)
            home = (F.col("group") * width + F.pmod(F.spark_partition_id(), F.lit(width))).cast("int")
            moved = cur.withColumn("home", home).repartitionById(p, "home").drop("home")
            run = Run(stage(moved, "round"), spec, lanes, moves=run.moves + exchanges(moved))
            cur = run.df
    run = Run(run.df.drop("group"), spec, lanes, moves=run.moves, total=first.n)
    return SortResult(run, fences, cur.withColumnRenamed("group", "bucket"), {"method": "iterated", "p": p, "k": k, "rounds": rounds, "r": r})


def balanced_sort(df: DataFrame, spec: SortSpec, p: int, machine: MachineModel | None = None, rows: int | None = None) -> SortResult:
    """The sort that the advisor chooses for the input in place: method, ratio, rounds and arity from its rows, partitions and the machine.

    rows is counted where it is not given. With rounds, p grows to the next power of the arity.
    """
    n = df.count() if rows is None else rows
    plan = advisor.choose(machine or MachineModel(p, *MACHINES[min(3, max(0, p.bit_length() - 5))][1:]), n, lanes=partitions(df), p=p)
    if plan.rounds > 1:
        return iterated_sort(df, spec, Lanes(plan.k**plan.rounds, layout="inplace"), plan.k, plan.rounds, r=max(1, min(6, plan.ratio)))
    if plan.method == "regular":
        return regular_sort(df, spec, Lanes(p, layout="inplace"), r=plan.ratio, split=plan.split)
    return presorted_random_sort(df, spec, Lanes(p, layout="inplace"), s=plan.ratio, split=plan.split)
