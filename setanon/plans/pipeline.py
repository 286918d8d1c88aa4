"""Anonymizing records: buckets, solver, edits, costs."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..llm.common import discard, written
from ..operators import kernel, lsh
from ..operators.kernel import FacilityOptions, SolveOptions
from ..operators.records import weight_of, weighted


@dataclass(frozen=True)
class AnonOptions:
    p: int = 3  # concatenated min-hashes of a bucket; 0 is one bucket
    hash: str = "xxhash64"  # md5 for runs that another engine reproduces
    solver: str = "suppress"
    candidates: str = "ball"
    overlap: bool = False
    popular_first: bool = True
    improve: bool = False
    ops: str = "both"
    tie: str = "delete"
    unit: str = "record"
    weights: tuple[float, float] = (1.0, 1.0)
    max_bucket: int = 2000
    on_empty: str = "publish"
    recenter: str = "majority"
    facility: FacilityOptions = field(default_factory=FacilityOptions)
    bucketing: str = "minhash"  # or pairs (all-pairs baseline), bands, mllib, given
    threshold: float = 0.5

    def solve(self, k: int) -> SolveOptions:
        return SolveOptions(k, self.solver, self.candidates, self.overlap, self.popular_first, self.improve, 3, self.ops, self.tie, self.unit, self.weights, self.recenter, 14, self.facility, self.on_empty)


@dataclass(frozen=True)
class AnonResult:
    """``solved(record_id, user_id, bucket_id, group_id, items, target)`` is held once; the other
    tables are projections of it."""

    solved: DataFrame
    dropped: DataFrame
    options: AnonOptions
    k: int
    held: tuple[DataFrame, ...] = ()  # what is written down

    def unpersist(self) -> None:
        for table in self.held:
            discard(table)

    @property
    def records(self) -> DataFrame:
        out = self.solved.select("record_id", "user_id", F.col("target").alias("items"))
        return out.where(F.size("items") > 0) if self.options.on_empty == "drop" else out

    @property
    def groups(self) -> DataFrame:
        return self.solved.select("record_id", "bucket_id", "group_id")

    @property
    def edits(self) -> DataFrame:
        """Insertions and deletions inside groups."""
        add = self.solved.select("record_id", F.explode(F.array_except("target", "items")).alias("item"), F.lit("add").alias("op"))
        gone = self.solved.select("record_id", F.explode(F.array_except("items", "target")).alias("item"), F.lit("del").alias("op"))
        return add.unionByName(gone)

    @property
    def cost(self) -> DataFrame:
        """(metric, value): insertions, deletions in groups and by dropped records, totals, counts."""
        inside = self.solved.agg(
            F.sum(F.size(F.array_except("target", "items"))).alias("add"),
            F.sum(F.size(F.array_except("items", "target"))).alias("del_in_group"),
            F.count(F.lit(1)).alias("records_kept"),
            F.count_distinct("bucket_id", "group_id").alias("groups"),
            F.count_if(F.size("target") == 0).alias("n_emptied"),
            F.sum(F.size("items")).alias("edges_kept"),
        )
        gone = self.dropped.agg(F.sum("n_items").alias("del_small_cluster"), F.count(F.lit(1)).alias("records_dropped"))
        row = inside.crossJoin(gone).na.fill(0)  # two single rows
        row = row.withColumn("total_in_group", F.col("add") + F.col("del_in_group")).withColumn("total", F.col("add") + F.col("del_in_group") + F.col("del_small_cluster"))
        return row.unpivot([], [c for c in row.columns], "metric", "value").select("metric", F.col("value").cast("double").alias("value"))


SOLVED = "record_id string, user_id string, bucket_id string, group_id string, items array<string>, target array<string>"


def bucketed(recs: DataFrame, o: AnonOptions) -> DataFrame:
    recs = recs.select("record_id", "user_id", "items", *(["bucket_id"] if o.bucketing == "given" else []))
    if o.bucketing == "given":
        return recs
    if o.bucketing == "pairs":
        return lsh.precluster_pairs(recs, o.threshold)
    if o.bucketing == "bands":
        return lsh.precluster_bands(recs, max(1, o.p), 4, o.hash)
    if o.bucketing == "mllib":
        return lsh.precluster_mllib(recs, o.threshold)
    return lsh.precluster(recs, o.p, o.hash)


def anonymize(recs: DataFrame, k: int, o: AnonOptions = AnonOptions()) -> AnonResult:
    """One exchange by bucket serves the count of small buckets, popular sets and the kernel.

    Sets that k records of a bucket hold, and that no kernel improves, become groups natively and
    never reach Python.
    """
    if k < 1:
        raise ValueError("k must be at least 1")
    b = bucketed(recs, o)
    if k == 1:
        done = b.select("record_id", "user_id", "bucket_id", F.col("record_id").alias("group_id"), "items", F.col("items").alias("target"))
        return AnonResult(done, b.where("false").select("record_id", F.size("items").alias("n_items")), o, k)
    b = written(b, "buckets")  # counted, then split; compressed, as a persisted table of sets is not
    kept, small = lsh.split_small(b, k, o.unit, keep_size=True, counted=True)
    kept = lsh.refine(kept, max(o.max_bucket, k), o.p, o.hash, k, o.unit)
    native = kept.where("false").select("record_id", "user_id", "bucket_id", F.lit("").alias("group_id"), "items", F.col("items").alias("target"))
    if o.popular_first and o.solver == "suppress" and o.unit == "record" and not o.improve:
        w, same = W.partitionBy("bucket_id"), W.partitionBy("bucket_id", F.concat_ws("\x1f", "items"))
        marked = kept.withColumn("_n", F.count(F.lit(1)).over(w)).withColumn("_m", F.count(F.lit(1)).over(same)).withColumn("_lead", F.min("record_id").over(same))
        marked = marked.withColumn("_rare", F.sum(F.when(F.col("_m") < k, 1).otherwise(0)).over(w))
        # a bucket's rare records go to the kernel when they can form groups; a few of them need the popular ones
        alone = (F.col("_m") >= k) & ((F.col("_rare") == 0) | (F.col("_rare") >= k))
        native = marked.where(alone).select("record_id", "user_id", "bucket_id", F.concat_ws("#", "bucket_id", "_lead").alias("group_id"), "items", F.col("items").alias("target"))
        kept = marked.where(~alone).select("record_id", "user_id", "bucket_id", "items")
    elif o.popular_first and o.solver == "facility" and o.unit == "record":
        # of a set's copies k stay to open a facility that other records may join; when k more or over are left, these are a group at no cost
        same = W.partitionBy("bucket_id", F.concat_ws("\x1f", "items"))
        marked = kept.withColumn("_m", F.count(F.lit(1)).over(same)).withColumn("_i", F.row_number().over(same.orderBy("record_id")))
        over = (F.col("_m") >= 2 * k) & (F.col("_i") > k)
        spare = marked.where(over).withColumn("_lead", F.min("record_id").over(same))
        native = spare.select("record_id", "user_id", "bucket_id", F.concat_ws("#", "bucket_id", "_lead").alias("group_id"), "items", F.col("items").alias("target"))
        kept = marked.where(~over).select("record_id", "user_id", "bucket_id", "items")
    opt = o.solve(k)

    def run(table):
        bucket = table.column("bucket_id")[0].as_py()
        ids, users, sets = (table.column(c).to_pylist() for c in ("record_id", "user_id", "items"))
        by = dict(zip(ids, zip(users, sets)))
        rows = [(i, by[i][0], bucket, f"{bucket}#{g}", by[i][1], t) for i, g, t in kernel.solve(ids, users, sets, opt)]
        left = by.keys() - {r[0] for r in rows}  # what the kernel refuses has no group
        rows += [(i, by[i][0], bucket, None, by[i][1], None) for i in sorted(left)]
        text, items = pa.string(), pa.list_(pa.string())
        schema = pa.schema([("record_id", text), ("user_id", text), ("bucket_id", text), ("group_id", text), ("items", items), ("target", items)])
        return pa.table([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * 6, schema)], schema=schema)

    solved = native.unionByName(kept.select("record_id", "user_id", "bucket_id", "items").groupBy("bucket_id").applyInArrow(run, SOLVED))
    solved = written(solved, "solved")  # several tables read it; kernels run once
    dropped = small.select("record_id", "items").unionByName(solved.where("group_id IS NULL").select("record_id", "items"))
    return AnonResult(solved.where("group_id IS NOT NULL"), dropped.select("record_id", F.size("items").alias("n_items")), o, k, (solved, b))


#: Unpopular records of a bucket whose sets the driver and every task of the rounds may hold.
HELD = 200_000


def suppress_rounds(recs: DataFrame, k: int, max_rounds: int = 200) -> DataFrame:
    """Cover rounds for a large bucket: all candidates are priced in parallel and those that are the
    cheapest for each of their records commit. Returns (record_id, group_id).

    Candidates are the balls of a record and its nearest ones among records that share an item.
    Up to ``HELD`` records are found their neighbours by all tasks, and the rounds go over the lists
    of these; more take rounds of joins. Records that no candidate holds any more are one group;
    rounds that run out are an error.
    """
    from ..operators.distance import knn
    from ..operators.graph import reliable
    from ..operators.rounds import held_rounds

    same = W.partitionBy("items")
    marked = reliable(recs.select("record_id", "user_id", "items").withColumn("_m", F.count(F.lit(1)).over(same)).withColumn("group_id", F.min("record_id").over(same)))
    popular = marked.where(F.col("_m") >= k).select("record_id", "group_id")  # they cost nothing, so the first rounds would commit them
    out = popular if popular.head(1) else None
    left = marked.where(F.col("_m") < k).select("record_id", "user_id", "items")
    held = left.limit(HELD + 1).count() <= HELD
    if held:
        new = recs.sparkSession.createDataFrame(held_rounds(left, k, max_rounds), "record_id string, group_id string")
        out = new if out is None and new.head(1) else out if out is None else out.unionByName(new)
        left = reliable(left.join(new, "record_id", "left_anti"))
    for _ in range(0 if held else max_rounds):
        near = knn(left, k - 1).groupBy("record_id").agg(F.collect_list("other").alias("others")).where(F.size("others") == k - 1)
        cand = near.select(F.col("record_id").alias("cand"), F.concat(F.array("record_id"), "others").alias("members"))
        cells = cand.select("cand", F.explode("members").alias("record_id")).join(left.select("record_id", "items"), "record_id").select("cand", F.explode("items").alias("item"))
        price = cells.groupBy("cand", "item").count().groupBy("cand").agg(F.sum(F.when(F.col("count") < k, 1).otherwise(0)).alias("price"))
        seats = cand.join(price, "cand").select("cand", "price", F.explode("members").alias("record_id"))
        seats = seats.withColumn("best", F.min(F.struct("price", "cand")).over(W.partitionBy("record_id")))
        won = seats.groupBy("cand").agg(F.min((F.col("best.cand") == F.col("cand")).cast("int")).alias("won"), F.collect_list("record_id").alias("members")).where("won = 1")
        new = reliable(won.select(F.explode("members").alias("record_id"), F.col("cand").alias("group_id")))
        if not new.head(1):
            break
        out = new if out is None else reliable(out.unionByName(new))
        left = reliable(left.join(new, "record_id", "left_anti"))
    else:
        if not held:
            raise RuntimeError(f"cover did not settle in {max_rounds} rounds")
    rest = left.select("record_id", F.lit("rest").alias("group_id"))
    n = left.limit(k).count()
    if out is None or n >= k:
        return rest if out is None else out.unionByName(rest)
    first = out.agg(F.min("group_id")).first()[0]
    return out.unionByName(rest.withColumn("group_id", F.lit(first)))


def bucketed_sets(recs: DataFrame, o: AnonOptions) -> DataFrame:
    """Distinct sets of each bucket: (bucket_id, items, record_id, weight)."""
    if o.bucketing == "minhash":
        return lsh.precluster(recs if "weight" in recs.columns else weighted(recs), o.p, o.hash)
    b = recs if o.bucketing == "given" else bucketed(recs, o)
    return b.groupBy("bucket_id", "items").agg(F.min("record_id").alias("record_id"), F.sum(weight_of(b)).alias("weight"))


_TOLD = ("add", "del_in_group", "records_kept", "groups", "n_emptied", "edges_kept", "del_small_cluster", "records_dropped")


def cost_of_sets(sets: DataFrame, k: int, o: AnonOptions) -> DataFrame:
    """``AnonResult.cost`` of ``bucketed_sets``, for units of single records. Copies are counted, not
    listed: runs of large buckets are cut by running totals, popular sets cost nothing, and only
    sets that a kernel must group are written out, inside its task.

    Copies have ids next to their set's least one, so a tie between ids may fall otherwise than in
    ``anonymize``."""
    most, opt, w = max(o.max_bucket, k), o.solve(k), W.partitionBy("bucket_id")
    more = lsh.minhash(F.col("items"), o.p + 7, o.hash).cast("string")
    n = sets.withColumn("_n", F.sum("weight").over(w))
    small = n.where(F.col("_n") < k).agg(F.sum(F.col("weight") * F.size("items")).alias("del_small_cluster"), F.sum("weight").alias("records_dropped"))
    kept = n.where(F.col("_n") >= k).withColumn("_end", F.sum("weight").over(w.orderBy(more, F.concat_ws("|", "items"), "record_id").rowsBetween(W.unboundedPreceding, 0)))
    last = F.greatest(F.floor(F.col("_n") / most), F.lit(1)) - 1
    run_of = lambda place: F.least(F.floor(place / most), last)
    cut = kept.withColumn("_last", last).withColumn("_run", F.explode(F.sequence(run_of(F.col("_end") - F.col("weight")), run_of(F.col("_end") - 1))))
    above = F.least("_end", F.when(F.col("_run") == F.col("_last"), F.col("_n")).otherwise((F.col("_run") + 1) * most))
    m = above - F.greatest(F.col("_end") - F.col("weight"), F.col("_run") * most)
    part = F.when(F.col("_n") > most, F.concat_ws("/", "bucket_id", F.col("_run").cast("string"))).otherwise(F.col("bucket_id"))
    pieces = cut.select(part.alias("bucket_id"), "record_id", "items", m.alias("m"))
    native = None
    if o.popular_first and o.solver == "suppress" and not o.improve:
        rare = F.sum(F.when(F.col("m") < k, F.col("m")).otherwise(0)).over(w)
        pieces = pieces.withColumn("_rare", rare)
        alone = (F.col("m") >= k) & ((F.col("_rare") == 0) | (F.col("_rare") >= k))
        zero = F.lit(0).cast("long")
        native = pieces.where(alone).agg(
            zero.alias("add"),
            zero.alias("del_in_group"),
            F.sum("m").alias("records_kept"),
            F.count(F.lit(1)).alias("groups"),
            F.sum(F.when(F.size("items") == 0, F.col("m")).otherwise(0)).alias("n_emptied"),
            F.sum(F.col("m") * F.size("items")).alias("edges_kept"),
            zero.alias("del_small_cluster"),
            zero.alias("records_dropped"),
        )
        pieces = pieces.where(~alone)

    def run(table):
        lead, sets, copies = (table.column(c).to_pylist() for c in ("record_id", "items", "m"))
        ids = [x if not i else f"{x}\x1f{i:09d}" for x, n in zip(lead, copies) for i in range(n)]
        own = dict(zip(ids, (set(s) for s, n in zip(sets, copies) for _ in range(n))))
        out, groups = dict.fromkeys(_TOLD, 0), set()
        for i, g, t in kernel.solve(ids, ids, [sorted(own[x]) for x in ids], opt):
            mine, goal = own.pop(i), set(t)
            groups.add(g)
            for key, value in (("add", len(goal - mine)), ("del_in_group", len(mine - goal)), ("records_kept", 1), ("n_emptied", not goal), ("edges_kept", len(mine))):
                out[key] += int(value)
        out |= {"groups": len(groups), "records_dropped": len(own), "del_small_cluster": sum(map(len, own.values()))}
        return pa.table({key: pa.array([value], pa.int64()) for key, value in out.items()})

    told = pieces.select("bucket_id", "record_id", "items", "m").groupBy("bucket_id").applyInArrow(run, ", ".join(f"{c} long" for c in _TOLD))
    parts = [told, small.select(*(F.col(c) if c in small.columns else F.lit(0).cast("long").alias(c) for c in _TOLD))]
    for other in [*parts[1:], *([native] if native is not None else [])]:
        told = told.unionByName(other)
    row = told.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in _TOLD))
    row = row.withColumn("total_in_group", F.col("add") + F.col("del_in_group")).withColumn("total", F.col("add") + F.col("del_in_group") + F.col("del_small_cluster"))
    return row.unpivot([], list(row.columns), "metric", "value").select("metric", F.col("value").cast("double").alias("value"))


def cost_curve(recs: DataFrame, ks: list[int], o: AnonOptions = AnonOptions()) -> DataFrame:
    """(k, metric, value); buckets, which do not depend on k, are made once, and where units are
    single records, of distinct sets only. Records may be ``weighted``."""
    by_sets = o.unit == "record" and min(ks) > 1
    b = (bucketed_sets(recs, o) if by_sets else bucketed(recs, o)).persist(StorageLevel.DISK_ONLY)
    given = replace(o, bucketing="given")
    out = None
    for k in ks:
        part = (cost_of_sets(b, k, o) if by_sets else anonymize(b, k, given).cost).withColumn("k", F.lit(k))
        out = part if out is None else out.unionByName(part)
    return out.select("k", "metric", "value")
