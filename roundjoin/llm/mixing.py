"""Mixing sources to target weights by systematic sampling: expected copies are summed up along each source, one random offset is added, and a
document is emitted once for each integer boundary that its share crosses. DataFrame functions only.

Prefix sums come from places in sorted order: rows are dealt by ranges of the order, and a row's place is its place in its partition plus the rows
of the partitions before, of which the driver gets one count each. So neither a source nor the list of sources is ever one task's.
"""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, pick, spread_join

#: Production values: weights in turn over the sources in order, total as a share of all words, cap on the copies of a document, rows
#: that a sorting task takes (there are as many tasks as the session's shuffles have, and more where these would take more rows).
WEIGHTS, TOTAL_SHARE, MAX_COPIES, BUCKET_ROWS, SEED = (3.0, 1.0, 2.0), 1.5, 2.0, 2_000_000, 11
_ROW_BITS = 33  # of monotonically_increasing_id; the bits above are the partition


def share_out(sizes: list[float], weights: list[float], total: float, cap: float) -> list[float]:
    """Targets in proportion to weights; each stops at cap times its size, and the excess goes to the others by weight until none is above."""
    targets, free, left = [0.0] * len(sizes), list(range(len(sizes))), float(total)
    while free:
        unit = left / sum(weights[i] for i in free)
        over = [i for i in free if weights[i] * unit > cap * sizes[i]]
        for i in over or free:
            targets[i] = cap * sizes[i] if over else weights[i] * unit
        if not over:
            break
        left -= sum(targets[i] for i in over)
        free = [i for i in free if i not in over]
    return targets


def placed(df: DataFrame, order: list[Column], name: str, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """df, a table, written in the given order, with each row's place in it (from 0)."""
    at, parts = F.monotonically_increasing_id(), -(-df.count() // bucket_rows)
    few = parts <= int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = cut((df.repartitionByRange(*order) if few else df.repartitionByRange(parts, *order)).sortWithinPartitions(*order).withColumn("__at", at))
    part = F.shiftright("__at", _ROW_BITS)
    counts = sorted((r.p, r.n) for r in rows.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect())
    before = list(accumulate((n for _, n in counts), initial=0))
    starts = df.sparkSession.createDataFrame([(p, b) for (p, _), b in zip(counts, before, strict=False)], "__p long, __b long")
    place = F.col("__b") + F.col("__at").bitwiseAND((1 << _ROW_BITS) - 1)
    return rows.withColumn("__p", part).join(F.broadcast(starts), "__p").withColumn(name, place).drop("__p", "__b", "__at")


def source_plan(totals: DataFrame, weights: tuple[float, ...], total_share: float, max_copies: float) -> DataFrame:
    """totals (source, source_size, others) with the target of each source. Only sums over sources come to the driver, in each round of resharing."""
    ranked = placed(totals, [F.col("source").isNull(), F.col("source")], "no")
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod("no", F.lit(len(weights))) + 1).cast("int"))
    plan = cut(ranked.withColumn("weight", weight).withColumn("most", max_copies * F.col("source_size")))
    sums = plan.agg(F.sum("source_size").alias("s"), F.sum("weight").alias("w")).first()
    total = total_share * (sums.s or 0)
    unit, capped = total / sums.w if sums.w else 0.0, 0
    while True:
        over = plan.where(F.col("weight") * unit > F.col("most")).agg(F.count("*").alias("n"), F.coalesce(F.sum("source_size"), F.lit(0)).alias("s"), F.coalesce(F.sum("weight"), F.lit(0.0)).alias("w")).first()
        if over.n == capped or over.w >= (sums.w or 0.0):
            break
        capped, unit = over.n, (total - max_copies * over.s) / (sums.w - over.w)
    return plan.withColumn("target", F.least(F.col("weight") * unit, F.col("most"))).drop("weight", "most", "no")


def plan_copies(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, total_share: float = TOTAL_SHARE, max_copies: float = MAX_COPIES, seed: int = SEED, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """Per row of docs: doc_id, source, size, source_size, target, copies.

    Sources stand by code point, null last (null is a source of its own). All documents of a source have the same expected copies, target over size, and
    stand by size, then a hash, then id, so the words taken differ from the target by less than the largest document of the source, whatever the offset.
    Null and empty texts have size 0 and copies like others of their source; a source of size 0 has target 0 and no copies; repeated rows each have their own
    share; ties stand by id, and equal rows are alike; an empty table gives no rows; other columns are ignored."""
    word = r"[^\x20\x09-\x0D]+"
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = pick(docs, "doc_id", "source", "text").select("doc_id", "source", F.regexp_count(text, F.lit(word)).cast("long").alias("size"), F.md5(F.concat_ws("|", F.col("doc_id").cast("string"), text)).alias("h"))
    rows = placed(cut(rows), [F.col("source"), F.col("size"), F.col("h"), F.col("doc_id")], "place", bucket_rows)
    rows = rows.withColumn("key", F.coalesce(F.concat(F.lit("s"), "source"), F.lit("-")))
    totals = rows.groupBy("key").agg(F.first("source").alias("source"), F.sum("size").alias("source_size"), F.count("*").alias("n"), F.min("place").alias("start"))
    plan = source_plan(cut(totals), weights, total_share, max_copies)
    # a fraction with 28 bits
    offset = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("key"))), 1, 7), 16, 10).cast("long") / float(1 << 28)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    plan = cut(plan.select("key", "source_size", "target", "n", "start", rate.alias("rate"), offset.alias("offset")))
    known = spread_join(rows, plan, "key", "h")
    k = F.col("place") - F.col("start")
    copies = F.floor(F.col("offset") + F.col("rate") * (k + 1)) - F.floor(F.col("offset") + F.col("rate") * k)
    return known.select("doc_id", "source", "size", "source_size", "target", copies.cast("long").alias("copies"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken (words that the mix takes of the row, repeats counted). Edge cases as in plan_copies."""
    return plan_copies(docs, **options).select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def emit(plan: DataFrame) -> DataFrame:
    """One row (doc_id, copy_no from 1) for each copy of a plan; rows without copies have none."""
    return plan.where("copies > 0").select("doc_id", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("copy_no"))
