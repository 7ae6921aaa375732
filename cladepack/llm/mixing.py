"""Mixing sources to target weights by a low-discrepancy schedule.

Every slot of the schedule holds one block of equal size. Slot t takes the point frac((t + 1) * golden ratio) of the unit
interval, or the van der Corput point of t, and the source into whose stretch of the cumulative target weights the point
falls; so any stretch of the schedule holds the sources near their weights. A source's slots are ranked; its rank r takes
block r of its stream of documents, which stand in a shuffled order and start anew once they are used up. The last block
of a source ends where its target ends.

Ranks and positions are sums over rows that lie before a row. They are taken in two steps - totals of small ranges of
the order, then within a range -, so a source that holds a third of all rows is not one task's work.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, maybe_broadcast

GOLDEN = (math.sqrt(5) - 1) / 2
WORDS = r"[^\x20\x09-\x0D]+"
#: Largest block, in words; smaller for small corpora, so that every source has some hundred blocks.
MOST_BLOCK = 4096
#: Rows of one range of the two-step sums.
RANGE_ROWS = 50_000


def source_targets(sizes: DataFrame, weights: list[float], share: float, most: float = 2.0) -> DataFrame:
    """(source, source_size, weight, target) from (source, source_size): sources in code-point order, null last, take the
    weights in turn and share `share` times all sizes by weight; no target passes `most` times its source's size, and what
    is cut off goes to the others by weight. That is the level L at which the targets min(most * size, L * weight) add up;
    the sources are capped in the order of size / weight."""
    order = Window.orderBy(F.col("source").isNull(), F.col("source"))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    by = Window.orderBy("ratio", F.col("source").isNull(), F.col("source"))
    before, every = by.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    cap = F.col("source_size") * F.lit(float(most))
    out = sizes.withColumn("weight", w).withColumn("cap", cap).withColumn("ratio", F.col("cap") / F.col("weight"))
    left = F.sum("source_size").over(every) * F.lit(float(share)) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))
    weight_left = F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    out = out.withColumn("level", left / weight_left).withColumn("full", F.col("ratio") <= F.col("level"))
    level = F.min(F.when(~F.col("full"), F.struct("ratio", F.col("source").isNull(), "source", "level"))).over(every)["level"]
    return out.withColumn("open", level).select("source", "source_size", "weight", F.when(F.col("full"), F.col("cap")).otherwise(F.col("open") * F.col("weight")).alias("target"))


def _before(rows: DataFrame, group: list[str], order: list[str], value: str, ranges: str, out: str, scratch: Scratch) -> DataFrame:
    """rows with column out: the sum of value over the rows of the group that come earlier. ranges: a column that splits
    the order of a group into stretches of bounded length."""
    keys = [*group, ranges]
    totals = rows.groupBy(*keys).agg(F.sum(value).alias("_t"))
    ahead = F.sum("_t").over(Window.partitionBy(*group).orderBy(ranges).rowsBetween(Window.unboundedPreceding, -1))
    starts = scratch.save(totals.withColumn("_s", F.coalesce(ahead, F.lit(0))).drop("_t"))
    inner = F.sum(value).over(Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
    joined = rows.withColumn("_in", F.coalesce(inner, F.lit(0))).join(maybe_broadcast(starts), keys)
    return joined.withColumn(out, F.col("_s") + F.col("_in")).drop("_s", "_in")


def point(t, kind: str):
    """The t-th point, t from 0, of the golden-ratio or the base-2 van der Corput sequence."""
    if kind == "golden":
        high, low = F.floor((t + 1) / 1048576), F.pmod(t + 1, F.lit(1048576))
        x = high * F.lit((GOLDEN * 1048576) % 1.0) + low * F.lit(GOLDEN)
        return x - F.floor(x)
    bits = F.reverse(F.lpad(F.bin(t), 48, "0"))
    return F.conv(bits, 2, 10).cast("double") / F.lit(float(1 << 48))


def schedule(targets: DataFrame, block: int, scratch: Scratch, kind: str = "golden") -> DataFrame:
    """(slot, source_id, rank) over targets (source_id, target): every source has ceil(floor(target) / block) slots, ranks
    from 0. Slots beyond that are void; what the points left out of a source comes at the end."""
    spark = targets.sparkSession
    need = targets.select("source_id", "target", F.ceil(F.floor("target") / block).cast("long").alias("need")).where("need > 0")
    order = Window.orderBy("source_id").rowsBetween(Window.unboundedPreceding, 0)
    bands = scratch.save(need.withColumn("to", F.sum("need").over(order)).withColumn("from", F.col("to") - F.col("need")))
    n = bands.agg(F.coalesce(F.sum("need"), F.lit(0))).first()[0]
    slots = spark.range(n).select(F.col("id").alias("slot"), (point(F.col("id"), kind) * F.lit(float(n))).alias("x"))
    # an equality on 1024ths of the interval leaves each slot one band or a few to compare with
    part = lambda c: F.floor(c * F.lit(1024.0 / max(n, 1)))
    cells = bands.select("source_id", "need", "from", "to", F.explode(F.sequence(part(F.col("from")), part(F.col("to")))).alias("cell"))
    held = slots.withColumn("cell", part(F.col("x"))).join(maybe_broadcast(cells), "cell").where("x >= from and x < to")
    held = held.select("slot", "source_id", "need", F.floor(F.col("slot") / RANGE_ROWS).alias("stretch"), F.lit(1).alias("one"))
    ranked = scratch.save(_before(held, ["source_id"], ["slot"], "one", "stretch", "rank", scratch).where("rank < need").select("slot", "source_id", "rank"))
    got = ranked.groupBy("source_id").agg(F.count("*").alias("got"))
    short = bands.join(got, "source_id", "left").withColumn("got", F.coalesce("got", F.lit(0))).where("got < need")
    tail = short.select("source_id", F.explode(F.sequence(F.col("got"), F.col("need") - 1)).alias("rank"))
    # missing ranks follow all slots, lowest ranks first
    tail = tail.select((F.lit(n) + F.col("rank")).alias("slot"), "source_id", "rank")
    return ranked.unionByName(tail)


def mix_sources(docs: DataFrame, weights: list[float] = (3, 1, 2), share: float = 1.5, kind: str = "golden", id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, source, size, source_size, target, taken, first_slot, n_pieces) for every row of docs.

    size is the number of words (runs other than ASCII white space), 0 for null; taken the words that the mix takes from
    the row, at most twice its size; over a source they add up to its target, rounded down. first_slot is the first slot of
    the schedule whose block holds words of the row (-1 if none is taken), which is where training meets it; n_pieces
    the number of blocks' pieces that come from it. Null sources are one source of their own. Rows with equal ids are
    shuffled next to each other, the smaller first; rows alike in id, source and size are interchangeable. Texts of any
    length are counted whole. Documents without words are never taken; an empty table gives an empty result; other columns
    are ignored.
    """
    scratch = Scratch(docs.sparkSession, "mixing")
    n_words = F.coalesce(F.regexp_count(F.col(text_col).cast("string"), F.lit(WORDS)), F.lit(0)).cast("long")
    rows = scratch.save(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), n_words.alias("size")))
    found = source_targets(rows.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs")).select("source", "source_size"), list(weights), share)
    ids = Window.orderBy(F.col("source").isNull(), F.col("source"))
    targets = scratch.save(found.withColumn("source_id", F.row_number().over(ids).cast("long")))
    facts = targets.agg(F.sum("source_size"), F.count("*")).first()
    n_rows = rows.count()
    block = max(1, min(MOST_BLOCK, (facts[0] or 0) // (256 * max(1, facts[1]))))
    plan = schedule(targets, block, scratch, kind)

    # a source's stream: documents by hash of their id; its ranges are stretches of that order
    n_ranges = max(1, -(-n_rows // RANGE_ROWS))
    mark = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    stretch = F.floor(F.conv(F.substring("mark", 1, 8), 16, 10).cast("double") * n_ranges / F.lit(4294967296.0))
    placed = rows.join(maybe_broadcast(targets), rows["source"].eqNullSafe(targets["source"])).drop(targets["source"]).withColumn("mark", mark).withColumn("stretch", stretch)
    placed = scratch.save(_before(placed, ["source_id"], ["mark", "doc_id", "size"], "size", "stretch", "start", scratch))

    # the stream runs twice at most; a document's words in run e stand at e * source_size + start
    runs = placed.where("size > 0").select("source_id", "start", "size", "target", F.explode(F.array(F.col("start"), F.col("start") + F.col("source_size"))).alias("at"))
    runs = runs.withColumn("end", F.least(F.col("at") + F.col("size"), F.floor("target"))).where("at < end")
    pieces = runs.withColumn("rank", F.explode(F.sequence(F.floor(F.col("at") / block), F.floor((F.col("end") - 1) / block))))
    cut = F.least(F.col("end"), (F.col("rank") + 1) * block) - F.greatest(F.col("at"), F.col("rank") * block)
    taken = pieces.withColumn("words", cut).join(plan, ["source_id", "rank"]).groupBy("source_id", "start").agg(F.sum("words").alias("taken"), F.min("slot").alias("first_slot"), F.count("*").alias("n_pieces"))
    out = placed.join(taken, ["source_id", "start"], "left")
    # rows without words share a start with the row after them
    of = lambda c: F.when(F.col("size") > 0, F.col(c))
    return out.select("doc_id", "source", "size", "source_size", F.col("target").cast("double").alias("target"), F.coalesce(of("taken"), F.lit(0)).cast("long").alias("taken"), F.coalesce(of("first_slot"), F.lit(-1)).cast("long").alias("first_slot"), F.coalesce(of("n_pieces"), F.lit(0)).cast("long").alias("n_pieces"))
