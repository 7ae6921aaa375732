"""Benchmark decontamination as a prefix-filtered set join, in DataFrame operations only.

A window is `window` consecutive words of an item, or the whole item if it has fewer. A document holds a window only if
it holds all its shingles, so one of them is a sufficient prefix, and the rarest in the documents is the best. Shingles
are ordered by the number of their occurrences in all documents; each window is filed under its rarest one. A document's
shingles are then joined with these prefix tokens; a hit at some position fixes where the window would have to lie, which
the document's length bounds, and the words there are compared with the window's, all of them.

The items are the small side. Their prefix tokens are broadcast while their counted number is within a limit; beyond it
the positions and keys of the shingles are shuffled to them, and those that meet one go back to the words of their row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, Scratch, ascii_lower, maybe_broadcast, numbered, without

#: Prefix tokens that are broadcast at most.
MOST_TOKENS = BROADCAST_ROWS
#: What separates words: ASCII other than digits and letters.
BREAKS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def split_words(text: Column) -> Column:
    """Words as they stand in the text; the first or last may be empty, which matches nothing."""
    return F.split(text.cast("string"), BREAKS)


def count_words(words: Column) -> Column:
    edge = lambda i: (F.get(words, i) == "").cast("int")
    one = F.size(words) == 1
    return F.when(words.isNull(), 0).when(one, 1 - edge(F.lit(0))).otherwise(F.size(words) - edge(F.lit(0)) - edge(F.size(words) - 1)).cast("long")


def _pair(words: Column, at: Column, word: Column) -> Column:
    """Key of the shingle of two words at a position; Unicode case is folded here and compared exactly later."""
    return F.xxhash64(F.lower(word), F.lower(F.get(words, at + 1)))


def item_windows(items: DataFrame, window: int, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """(item_id, start, len, words, text): the windows of every item; items without words have none."""
    words = F.filter(split_words(ascii_lower(F.col(text_col))), lambda x: x != "")
    rows = items.select(F.col(id_col).cast("string").alias("item_id"), words.alias("ws")).where("size(ws) > 0").distinct()
    rows = rows.withColumn("len", F.least(F.size("ws"), F.lit(window)))
    rows = rows.withColumn("start", F.explode(F.sequence(F.lit(0), F.size("ws") - F.col("len"))))
    return rows.select("item_id", "start", "len", F.slice("ws", F.col("start") + 1, F.col("len")).alias("words")).withColumn("text", F.array_join("words", " "))


def prefix_tokens(windows: DataFrame, docs: DataFrame, scratch: Scratch, text_col: str = "text") -> DataFrame:
    """(key, single, spots): for each prefix token the windows filed under it. spots holds (at, len, text) with the place
    of the token in the window. One-word windows are filed under the word itself."""
    texts = windows.groupBy("text", "len").agg(F.first("words").alias("words"))
    single = texts.where("len = 1").select(F.xxhash64(F.lower("text")).alias("key"), F.lit(0).alias("at"), "len", "text")
    pairs = texts.where("len > 1").select("len", "text", F.posexplode("words").alias("at", "word"), "words").where("at + 1 < len")
    pairs = scratch.save(pairs.select(_pair(F.col("words"), F.col("at"), F.col("word")).alias("key"), "at", "len", "text"))
    # rarity: occurrences of the items' shingles in all documents
    keys = pairs.select("key").distinct()
    words = docs.select(split_words(F.col(text_col)).alias("ws"))
    seen = words.select(F.posexplode_outer("ws").alias("at", "word"), "ws").select(_pair(F.col("ws"), F.col("at"), F.col("word")).alias("key"))
    counts = scratch.save(seen.join(maybe_broadcast(keys), "key").groupBy("key").agg(F.count("*").alias("n")))
    ranked = pairs.join(counts, "key", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    best = ranked.groupBy("text", "len").agg(F.min(F.struct("n", "key", "at")).alias("b")).select(F.col("b.key").alias("key"), F.col("b.at").alias("at"), "len", "text")
    filed = best.withColumn("single", F.lit(False)).unionByName(single.withColumn("single", F.lit(True)))
    return scratch.save(filed.groupBy("key", "single").agg(F.collect_list(F.struct("at", "len", "text")).alias("spots")))


def covered(spans: Column) -> Column:
    """Number of positions that the (start, end) spans of an array cover together."""
    step = lambda acc, s: F.struct(
        (acc["n"] + F.greatest(F.lit(0), s["end"] - F.greatest(s["start"], acc["to"]))).cast("long").alias("n"),
        F.greatest(acc["to"], s["end"]).alias("to"),
    )
    return F.aggregate(F.array_sort(spans), F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).alias("to")), step)["n"]


def decontaminate(docs: DataFrame, items: DataFrame, window: int = 13, num: int = 1, den: int = 20, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_words, n_hit, n_items, item_ids, contaminated) for every row of docs.

    A word inside an occurrence of a window is hit; a document is contaminated if it has hits and den * n_hit >= num *
    n_words. Null and empty texts have no words. Repeated items count by their distinct ids; items without words never
    occur. Rows with equal or null ids stay rows of their own. An empty table on either side is allowed; other columns
    are ignored.
    """
    scratch = Scratch(docs.sparkSession, "decontaminate")
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    windows = scratch.save(item_windows(items, window))
    tokens = prefix_tokens(windows, text, scratch)
    facts = tokens.agg(F.count("*"), F.coalesce(F.sum(F.col("single").cast("int")), F.lit(0))).first()

    # rows are numbered, so that those with equal or null ids stay apart
    base = text.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text")
    split = split_words(F.col("text")).alias("ws")
    if facts[0] <= MOST_TOKENS:  # one job reads the numbers
        words = base.select("row", "doc_id", split)
        at = words.select("row", "doc_id", "ws", F.posexplode_outer("ws").alias("at", "word"))
        pair = tokens.where("not single").select(F.col("key").alias("key"), F.col("spots"))
        hits = at.withColumn("key", _pair(F.col("ws"), F.col("at"), F.col("word"))).join(maybe_broadcast(pair, facts[0], MOST_TOKENS), "key", "left")
        if facts[1]:  # windows of one word: few, and only with such items
            one = tokens.where("single").select(F.col("key").alias("key1"), F.col("spots").alias("spots1"))
            hits = hits.withColumn("key1", F.xxhash64(F.lower("word"))).join(maybe_broadcast(one, facts[1], MOST_TOKENS), "key1", "left")
            hits = hits.withColumn("spots", F.when(F.col("spots").isNull(), F.col("spots1")).when(F.col("spots1").isNull(), F.col("spots")).otherwise(F.concat("spots", "spots1")))
        # of a document's words only the first and those that meet a token go on
        kept = hits.withColumn("head", F.coalesce("at", F.lit(0)) == 0).where("spots is not null or head")
    else:  # positions and keys are shuffled to the tokens, and only those that meet one go back to their words
        words = scratch.save(base).select("row", "doc_id", split)
        at = words.select("row", "ws", F.posexplode("ws").alias("at", "word"))
        keyed = at.select("row", "at", F.explode(F.array(F.struct(_pair(F.col("ws"), F.col("at"), F.col("word")).alias("key"), F.lit(False).alias("single")), F.struct(F.xxhash64(F.lower("word")).alias("key"), F.lit(True).alias("single")))).alias("k")).select("row", "at", "k.*")
        met = scratch.save(keyed.where("single = false" if not facts[1] else "true").join(tokens, ["key", "single"]).select("row", "at", "spots"))
        heads = words.select("row", "doc_id", "ws", F.lit(0).alias("at"), F.lit(None).cast(met.schema["spots"].dataType).alias("spots"), F.lit(True).alias("head"))
        kept = heads.unionByName(words.join(met, "row").withColumn("head", F.lit(False)))
    place = lambda s: F.array_join(F.slice(F.col("ws"), F.col("at") - s["at"] + 1, s["len"]), " ")
    fits = lambda s: F.when((F.col("at") >= s["at"]) & (F.col("at") - s["at"] + s["len"] <= F.size("ws")), ascii_lower(place(s)) == s["text"]).otherwise(F.lit(False))
    found = F.transform(F.filter("spots", fits), lambda s: F.struct((F.col("at") - s["at"]).alias("start"), (F.col("at") - s["at"] + s["len"]).alias("end"), s["text"].alias("text")))
    n_words = F.when(F.col("head"), count_words(F.col("ws"))).otherwise(F.lit(0).cast("long"))
    rows = kept.select("row", "doc_id", n_words.alias("n_words"), found.alias("found"))
    per_doc = rows.groupBy("row").agg(F.first("doc_id").alias("doc_id"), F.sum("n_words").alias("n_words"), F.flatten(F.collect_list("found")).alias("found"))
    per_doc = per_doc.select("row", "doc_id", "n_words", covered(F.transform("found", lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end")))).alias("n_hit"), F.array_distinct(F.transform("found", lambda x: x["text"])).alias("texts"))
    per_doc = scratch.save(per_doc)
    owners = windows.select("text", "item_id").distinct()
    named = per_doc.where("size(texts) > 0").select("row", F.explode("texts").alias("text")).join(maybe_broadcast(owners), "text")
    named = named.groupBy("row").agg(F.array_sort(F.collect_set("item_id")).alias("item_ids"))
    out = per_doc.join(named, "row", "left").withColumn("item_ids", F.coalesce("item_ids", F.array().cast("array<string>")))
    bad = (F.col("n_hit") > 0) & (F.lit(den) * F.col("n_hit") >= F.lit(num) * F.col("n_words"))
    return out.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), "item_ids", bad.alias("contaminated"))


def drop_contaminated(docs: DataFrame, items: DataFrame, window: int = 13) -> DataFrame:
    """The rows of docs that are not contaminated, columns unchanged; each row is judged by its own text, whatever its id."""
    scratch = Scratch(docs.sparkSession, "contaminated")
    rows, row = numbered(scratch, docs)
    return without(rows, row, decontaminate(rows, items, window, id_col=row).where("contaminated").select(F.col("doc_id").alias("row")))
