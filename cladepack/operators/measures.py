"""Sizes, ratios, times and accuracy of the codecs."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import codec as cd


def raw_size(trees: DataFrame) -> DataFrame:
    """(n_trees, raw_bytes): Newick lines with their line ends."""
    return trees.agg(F.count("*").alias("n_trees"), F.coalesce(F.sum(F.octet_length("newick") + 1), F.lit(0)).alias("raw_bytes"))


def compression_ratio(raw: Column, packed: Column) -> Column:
    return raw / packed


def space_saving(raw: Column, packed: Column) -> Column:
    return (1 - 1 / compression_ratio(raw, packed)) * 100


def relative(ours: Column, base: Column) -> Column:
    """Our size or time as a percentage of the baseline's; the cut is 100 less that."""
    return ours / base * 100


def speedup(base: Column, ours: Column) -> Column:
    return base / ours


def container_size(container: DataFrame) -> DataFrame:
    """Bytes of all that is stored: payload, list of trees, side data and header."""
    part = lambda c: F.coalesce(F.octet_length(c), F.lit(0))
    header = F.octet_length(F.array_join("taxa", ":")) + 24
    return container.agg(F.sum(part("payload") + part("trees") + part("lengths") + part("labels") + header).alias("comp_bytes"), F.sum("raw_bytes").alias("buffer_bytes"), F.sum("n_bip").alias("n_entries"))


def count_bipartitions(container: DataFrame, n_taxa: int) -> DataFrame:
    """n_all: inner clusters and the root of every tree, and a trivial one for each taxon; n_unique: distinct inner ones."""
    from .consensus import cluster_supports

    found = cluster_supports(container).agg(F.coalesce(F.sum("n_support"), F.lit(0)).alias("members"), F.count("*").alias("n_unique"))
    trees = container.agg(F.sum("n_trees").alias("t"))
    return found.join(trees, F.lit(True)).select((F.col("members") + F.col("t") + n_taxa).alias("n_all"), "n_unique")


def dataset_properties(trees: DataFrame, container: DataFrame, name: str) -> DataFrame:
    n_taxa = len(container.select("taxa").first()["taxa"])
    return raw_size(trees).join(count_bipartitions(container, n_taxa), F.lit(True)).select(F.lit(name).alias("dataset"), F.lit(n_taxa).alias("n_taxa"), "n_trees", "n_all", "n_unique", "raw_bytes")


def size_report(spark: SparkSession, sizes: list[tuple[str, str, int, int]], base: str = "textrun") -> DataFrame:
    """One row for each dataset and codec from (dataset, codec, raw, packed): ratio, saving, relative size to the baseline
    where that has a result."""
    df = spark.createDataFrame(sizes, "dataset string, codec string, raw_bytes long, comp_bytes long")
    against = df.where(F.col("codec") == base).select("dataset", F.col("comp_bytes").alias("base_bytes"))
    out = df.join(F.broadcast(against), "dataset", "left")
    return out.select("dataset", "codec", "raw_bytes", "comp_bytes", compression_ratio(F.col("raw_bytes"), F.col("comp_bytes")).alias("ratio"), space_saving(F.col("raw_bytes"), F.col("comp_bytes")).alias("saving_pct"), relative(F.col("comp_bytes"), F.col("base_bytes")).alias("relative_pct"))


def macro_average(report: DataFrame) -> DataFrame:
    """Mean over datasets of every measure, by codec; datasets without a baseline result are left out of its mean."""
    return report.groupBy("codec").agg(F.avg("ratio").alias("ratio"), F.avg("saving_pct").alias("saving_pct"), F.avg("relative_pct").alias("relative_pct"), F.count("*").alias("n_datasets"))


def size_cube(report: DataFrame) -> DataFrame:
    return report.cube("dataset", "codec").agg(F.sum("comp_bytes").alias("comp_bytes"), F.count("*").alias("n_rows"))


def accuracy_report(trees: DataFrame, container: DataFrame) -> DataFrame:
    """Share of trees restored exactly: shape alone, with labels, with lengths."""
    rows = [cd.verify_roundtrip(trees, container, *how).agg(F.avg(F.col("ok").cast("double")).alias("share")).withColumn("what", F.lit(name)) for name, how in (("shape", (False, False)), ("labels", (True, False)), ("lengths", (False, True)))]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


def length_error(a: DataFrame, b: DataFrame) -> DataFrame:
    """Largest difference of the lengths of leaf edges between two collections, by tree and taxon."""
    from .newick import parse_newick

    one = parse_newick(a).where("is_leaf").select("tree_id", "label", F.col("length").alias("x"))
    two = parse_newick(b).where("is_leaf").select("tree_id", "label", F.col("length").alias("y"))
    return one.join(two, ["tree_id", "label"]).agg(F.max(F.abs(F.col("x") - F.col("y"))).alias("max_error"))


def speed_report(spark: SparkSession, rows: list[dict], base: str = "textrun") -> DataFrame:
    """(dataset, codec, comp_s, decomp_s, comp_speedup, decomp_speedup, comp_pct, decomp_pct) from results of run_codec with
    their dataset: times, the baseline's time as a multiple of ours, and ours as a percentage of the baseline's. Null where
    the baseline has not run."""
    df = spark.createDataFrame([(r["dataset"], r["codec"], float(r["comp_s"]), float(r["decomp_s"])) for r in rows], "dataset string, codec string, comp_s double, decomp_s double")
    against = df.where(F.col("codec") == base).select("dataset", F.col("comp_s").alias("b"), F.col("decomp_s").alias("e"))
    out = df.join(F.broadcast(against), "dataset", "left")
    ours = {"comp": ("comp_s", "b"), "decomp": ("decomp_s", "e")}
    return out.select(*df.columns, *[speedup(F.col(y), F.col(x)).alias(f"{k}_speedup") for k, (x, y) in ours.items()], *[relative(F.col(x), F.col(y)).alias(f"{k}_pct") for k, (x, y) in ours.items()])


def stage_seconds(spark: SparkSession, trees: DataFrame, folder: str, codec: str = "packed") -> dict[str, float]:
    """Seconds of the stages of packing and restoring, each as the time that a plan takes beyond the one that ends before
    it: parse (clusters of the pieces), encode (meeting and coding), finish (blocks and Deflate); decode (inflating and
    taking the clusters of each tree), rebuild (trees and their texts)."""
    taxa = cd.taxa_of(trees)
    spans = {r["b"]: r["s"] + 1 for r in trees.groupBy(F.floor(F.col("tree_id") / cd.BLOCK_TREES).cast("int").alias("b")).agg(F.max((F.col("tree_id") % cd.BLOCK_TREES).cast("int")).alias("s")).collect()}
    text = ("textrun", "textrun") if codec == "textrun" else ("packed", "packed")
    run = lambda df: timed(lambda: df.write.format("noop").mode("overwrite").save())[0]
    entries = cd.cluster_entries(trees, taxa)
    path = f"{folder}/stages_{codec}"
    cd.compress(trees, codec, taxa=taxa).write.mode("overwrite").option("compression", "none").parquet(path)
    container = spark.read.parquet(path)
    parse, encode, whole = run(entries), run(cd.encode_entries(entries, len(taxa), spans, *text)), run(cd.compress(trees, codec, taxa=taxa))
    plan = cd.restore_plan(container)
    decode, restore = run(cd.container_entries(container).select("bits", "n_support")), run(cd.decompress(container, **plan))
    return {"parse_s": parse, "encode_s": max(0.0, encode - parse), "finish_s": max(0.0, whole - encode), "decode_s": decode, "rebuild_s": max(0.0, restore - decode)}


def timed(action) -> tuple[float, object]:
    t = time.perf_counter()
    out = action()
    return time.perf_counter() - t, out


def run_codec(spark: SparkSession, trees: DataFrame, codec: str, folder: str, **options) -> dict:
    """Compress to Parquet, restore to Parquet, and the measures of both."""
    path = f"{folder}/{codec}"
    comp_s, _ = timed(lambda: cd.compress(trees, codec, **options).write.mode("overwrite").option("compression", "none").parquet(path))
    container = spark.read.parquet(path)
    dec_s, _ = timed(lambda: cd.decompress(container, **cd.restore_plan(container)).write.mode("overwrite").parquet(path + "_restored"))
    sizes, raw = container_size(container).first(), raw_size(trees).first()
    return {"codec": codec, "n_trees": raw["n_trees"], "raw_bytes": raw["raw_bytes"], "comp_bytes": sizes["comp_bytes"], "n_entries": sizes["n_entries"], "comp_s": comp_s, "decomp_s": dec_s}
