"""Tree collections derived from relational tables: nested sets that SQL defines, and their Newick texts.

Every forest is a table (tree_id, members) of proper clusters, members being zero-padded ordinals joined by commas. The
texts run in Spark and, with the other dialect, in DuckDB.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..kernels import newick as nw
from ..kernels import trees as tk


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Dialect:
    """The few spots where the two engines differ."""

    def __init__(self, duck: bool):
        self.duck = duck

    def members(self, x: str, width: int) -> str:
        if self.duck:
            return f"string_agg(lpad(CAST({x} AS VARCHAR), {width}, '0'), ',' ORDER BY {x})"
        # lpad would cut what is longer than the width
        return f"array_join(transform(array_sort(collect_list({x})), v -> lpad(CAST(v AS STRING), greatest({width}, length(CAST(v AS STRING))), '0')), ',')"

    def series(self, lo: str, hi: str, name: str) -> str:
        """A lateral list of the integers lo..hi."""
        return f"CROSS JOIN (SELECT unnest(range({lo}, ({hi}) + 1)) AS {name})" if self.duck else f"LATERAL VIEW explode(sequence({lo}, {hi})) AS {name}"

    def div(self, a: str, b: str) -> str:
        return f"(({a}) // ({b}))" if self.duck else f"(({a}) div ({b}))"

    def bit_of_embedding(self, d: str) -> str:
        return f"(CASE WHEN embedding[({d}) + 1] > 0 THEN 1 ELSE 0 END)" if self.duck else f"(CASE WHEN get(embedding, CAST({d} AS INT)) > 0 THEN 1 ELSE 0 END)"

    def days(self, x: str) -> str:
        return f"date_diff('day', DATE '1995-01-01', CAST({x} AS DATE))" if self.duck else f"datediff({x}, DATE '1995-01-01')"

    def hours(self, x: str) -> str:
        return f"date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', {x}))" if self.duck else f"CAST((unix_timestamp({x}) - unix_timestamp(TIMESTAMP '2024-01-01')) div 3600 AS BIGINT)"

    def nation_grid(self, cols: str) -> str:
        """Every nation beside each row: a dimension of 25 rows, carried as an array."""
        if self.duck:
            return f"CROSS JOIN (SELECT {cols} FROM nation)"
        return f"LATERAL VIEW inline((SELECT collect_list(struct({cols})) FROM nation)) AS {cols}"


def nat_sql(d: Dialect) -> str:
    """Monthly trees of nations: clusters with label and value in cents. CTE names: nat_leaf, nat."""
    return f"""
nat_v AS (SELECT CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS BIGINT) AS tree_id, c_nationkey AS nk, sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS cents
  FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2),
nat_t AS (SELECT DISTINCT tree_id FROM nat_v),
nat_g AS (SELECT tree_id, n_nationkey, n_regionkey FROM nat_t {d.nation_grid("n_nationkey, n_regionkey")}),
nat_leaf AS (SELECT g.tree_id, g.n_nationkey AS taxon, g.n_regionkey AS region, CAST(coalesce(v.cents, 0) AS BIGINT) AS cents,
  row_number() OVER (PARTITION BY g.tree_id, g.n_regionkey ORDER BY coalesce(v.cents, 0) DESC, g.n_nationkey) - 1 AS r
  FROM nat_g g LEFT JOIN nat_v v ON v.tree_id = g.tree_id AND v.nk = g.n_nationkey),
nat_c AS (SELECT tree_id, region, taxon, cents, r, level FROM nat_leaf {d.series("0", "3", "level")}),
nat AS (SELECT tree_id, {d.members("taxon", 2)} AS members, CAST(count(*) AS INT) AS card, CAST(sum(cents) AS BIGINT) AS cents, min(CASE WHEN level = 0 THEN r_name END) AS label
  FROM nat_c JOIN region ON r_regionkey = region
  WHERE level = 0 OR (level = 1 AND r <= 1) OR (level = 2 AND r >= 2) OR (level = 3 AND r >= 3) GROUP BY tree_id, region, level)"""


def sup_sql(d: Dialect) -> str:
    """Daily trees of suppliers. CTE names: sup_t, sup_day, sup."""
    return f"""
sup_n AS (SELECT CAST(count(*) AS INT) AS n FROM supplier),
sup_day AS (SELECT CAST({d.days("l_shipdate")} AS BIGINT) AS tree_id, l_suppkey AS taxon, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS cents FROM lineitem GROUP BY 1, 2),
sup_t AS (SELECT DISTINCT tree_id FROM sup_day),
sup_s AS (SELECT s_suppkey AS taxon, n_nationkey AS nk, n_regionkey AS rk FROM supplier JOIN nation ON s_nationkey = n_nationkey),
sup_fixed AS (SELECT {d.members("taxon", 4)} AS members, CAST(count(*) AS INT) AS card FROM sup_s GROUP BY rk UNION SELECT {d.members("taxon", 4)} AS members, CAST(count(*) AS INT) AS card FROM sup_s GROUP BY nk),
sup_active AS (SELECT tree_id, {d.members("s.taxon", 4)} AS members, CAST(count(*) AS INT) AS card FROM sup_day JOIN sup_s s ON s.taxon = sup_day.taxon GROUP BY tree_id, nk),
sup AS (SELECT tree_id, members, card FROM sup_t JOIN sup_fixed ON card >= 2 AND card < (SELECT n FROM sup_n)
  UNION SELECT tree_id, members, card FROM sup_active WHERE card >= 2 AND card < (SELECT n FROM sup_n))"""


def _h(d: Dialect, t: str, k: str) -> str:
    return d.div(f"(7919 * CAST({t} AS BIGINT) + 104729 * ({k}) + 12345) * 2654435761 % 4294967296", "65536")


def _prefix_sql(d: Dialect, name: str, source: str, n: int | None, trees: int, depth: int, noise: int, bits: int, bit: str, width: int, rows: str) -> str:
    pair = f"CASE WHEN {_h(d, 't', d.div('k', '2'))} % 100 < 30 THEN (CASE WHEN k % 2 = 0 THEN k + 1 ELSE k - 1 END) ELSE k END"
    dim = f"CASE WHEN {_h(d, 't', '1000 + k')} % 100 < {noise} THEN {depth} + {_h(d, 't', '2000 + k')} % ({bits} - {depth}) ELSE {pair} END"
    start = "(SELECT 1 AS one)"
    return f"""
{name}_t AS (SELECT CAST(t AS BIGINT) AS t FROM {start} x {d.series("0", str(trees - 1), "t")}),
{name}_d AS (SELECT t, CAST(k AS BIGINT) AS k, CAST({dim} AS INT) AS dim FROM {name}_t {d.series("0", str(depth - 1), "k")}),
{name}_b AS (SELECT t, k, taxon, {bit} AS b FROM {name}_d JOIN {source} ON true),
{name}_p AS (SELECT t, k, taxon, sum(b * CAST(pow(2, k) AS BIGINT)) OVER (PARTITION BY t, taxon ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS p FROM {name}_b),
{name} AS (SELECT DISTINCT t AS tree_id, {d.members("taxon", width)} AS members, CAST(count(*) AS INT) AS card FROM {name}_p GROUP BY t, k, p HAVING count(*) >= 2 AND count(*) < {f'(SELECT count(*) FROM {rows})' if n is None else n})"""


def emb_sql(d: Dialect, n: int | None, trees: int, depth: int, noise: int) -> str:
    """Prefix trees over the first n vectors, or over all of them without n."""
    source = f"(SELECT CAST(vec_id AS INT) AS taxon, embedding FROM embeddings {'' if n is None else f'WHERE vec_id < {n}'}) e"
    return _prefix_sql(d, "emb", source, n, trees, depth, noise, 64, d.bit_of_embedding("dim"), 4, "embeddings")


def md5_sql(d: Dialect, n: int | None, trees: int, depth: int, noise: int) -> str:
    text = "VARCHAR" if d.duck else "STRING"
    source = f"(SELECT CAST(c_custkey AS INT) AS taxon, md5(CAST(c_custkey AS {text})) AS digest FROM customer {'' if n is None else f'WHERE c_custkey < {n}'}) e"
    digit = f"(instr('0123456789abcdef', substr(digest, CAST({d.div('dim', '4')} AS INT) + 1, 1)) - 1)"
    bit = f"CAST({d.div(digit, 'CAST(pow(2, 3 - dim % 4) AS INT)')} % 2 AS INT)"
    return _prefix_sql(d, "md5f", source, n, trees, depth, noise, 128, bit, 5, "customer")


def brand_sql(d: Dialect) -> str:
    """One tree of brands for each part size, by dyadic rank."""
    return f"""
br_v AS (SELECT p_size, p_brand, sum(CAST(round(p_retailprice * 100) AS BIGINT)) AS cents FROM part GROUP BY 1, 2),
br_o AS (SELECT p_brand, CAST(row_number() OVER (ORDER BY p_brand) - 1 AS INT) AS taxon FROM (SELECT DISTINCT p_brand FROM part)),
br_t AS (SELECT DISTINCT p_size FROM part),
br_r AS (SELECT t.p_size, o.taxon, row_number() OVER (PARTITION BY t.p_size ORDER BY coalesce(v.cents, 0) DESC, o.p_brand) - 1 AS r
  FROM br_t t JOIN br_o o ON true LEFT JOIN br_v v ON v.p_size = t.p_size AND v.p_brand = o.p_brand),
br_l AS (SELECT p_size, taxon, r, level FROM br_r {d.series("1", "4", "level")}),
brand AS (SELECT DISTINCT CAST(p_size AS BIGINT) AS tree_id, {d.members("taxon", 2)} AS members, CAST(count(*) AS INT) AS card FROM br_l
  GROUP BY p_size, level, {d.div("r * CAST(pow(2, level) AS BIGINT)", "(SELECT count(*) FROM br_o)")} HAVING count(*) >= 2)"""


def evt_sql(d: Dialect, events: str = "events") -> str:
    """One tree of 16 user buckets for each hour, by dyadic rank of their events."""
    return f"""
ev_v AS (SELECT {d.hours("ts")} AS tree_id, CAST(user_id % 16 AS INT) AS taxon, count(*) AS n FROM {events} GROUP BY 1, 2),
ev_t AS (SELECT DISTINCT tree_id FROM ev_v),
ev_g AS (SELECT tree_id, CAST(taxon AS INT) AS taxon FROM ev_t {d.series("0", "15", "taxon")}),
ev_r AS (SELECT g.tree_id, g.taxon, row_number() OVER (PARTITION BY g.tree_id ORDER BY coalesce(n, 0) DESC, g.taxon) - 1 AS r FROM ev_g g LEFT JOIN ev_v v ON v.tree_id = g.tree_id AND v.taxon = g.taxon),
ev_l AS (SELECT tree_id, taxon, r, level FROM ev_r {d.series("1", "3", "level")}),
evt AS (SELECT CAST(tree_id AS BIGINT) AS tree_id, {d.members("taxon", 2)} AS members, CAST(count(*) AS INT) AS card FROM ev_l GROUP BY tree_id, level, {d.div("r * CAST(pow(2, level) AS BIGINT)", "16")})"""


SPARK, DUCK = Dialect(False), Dialect(True)


def run_sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """Run a text over the tables of a folder."""
    for name in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings", "documents", "pages", "conversations"):
        if f"{name} " in text or f"{name})" in text or f"{name}\n" in text:
            table(spark, sf_dir, name).createOrReplaceTempView(name)
    return spark.sql(text)


# --- Newick texts -------------------------------------------------------------------------------------------------


def forest_newick(clusters: DataFrame, labels: list[str], leaves: DataFrame | None = None) -> DataFrame:
    """(tree_id, newick) of a forest (tree_id, members[, label, cents]); leaves: (tree_id, taxon, cents) of the leaf edges.
    Lengths are cents / 100 in the shortest form of their double. A tree's clusters are one row."""
    extra = [c for c in ("label", "cents") if c in clusters.columns]
    packed = clusters.groupBy("tree_id").agg(F.collect_list(F.struct("members", *extra)).alias("c"))
    if leaves is not None:
        packed = packed.join(leaves.groupBy("tree_id").agg(F.map_from_entries(F.collect_list(F.struct(F.col("taxon").cast("int"), "cents"))).alias("v")), "tree_id", "left")
    n = len(labels)

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1).to_pylist()[0]
                made = sorted(row["c"], key=lambda c: (len(c["members"]), c["members"]))
                sets = [np.array(c["members"].split(","), np.int64) for c in made]
                order = np.argsort([len(s) for s in sets], kind="stable") if sets else []
                made, sets = [made[k] for k in order], [sets[k] for k in order]
                kids = nested_children(sets, n)
                label = [*labels, *[c.get("label") for c in made], None]
                length: list[str | None] = [None] * len(label)
                if row.get("v") is not None:
                    v = dict(row["v"])
                    for x in range(n):
                        length[x] = repr(v.get(x, 0) / 100)
                    for k, c in enumerate(made):
                        length[n + k] = repr(c["cents"] / 100)
                yield pa.RecordBatch.from_arrays([pa.array([row["tree_id"]], pa.int64()), pa.array([nw.write(len(kids) - 1, kids, label, length)])], ["tree_id", "newick"])

    return packed.mapInArrow(run, "tree_id long, newick string")


def nested_children(sets: list[np.ndarray], n: int) -> list[list[int]]:
    """Child lists of the tree of nested sets of ordinals below n, given by ascending size."""
    sets = [*sets, np.arange(n)]
    leaf, cluster = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    order = np.argsort(leaf, kind="stable")
    return tk.children_lists(*tk.walk_paths(leaf[order], cluster[order], n, len(sets)))


def _hash(t: int, k: np.ndarray) -> np.ndarray:
    return ((7919 * t + 104729 * k + 12345) * 2654435761 % 4294967296) // 65536


def prefix_newick(t: int, bits: np.ndarray, labels: list[str], depth: int, noise: int) -> str:
    """Newick text of one replicate of a prefix forest: taxa in the order of their sign strings, in which every cluster is
    a run of equal prefixes."""
    order, intervals = _prefix_runs(t, bits, depth, noise)
    n = len(bits)
    out: list[str] = []
    starts: list[list[int]] = [[] for _ in range(n)]
    for a, b in intervals:
        starts[a].append(b)
    ends = [0] * n
    for a, b in intervals:
        ends[b] += 1
    for i in range(n):
        out.append("," if i else "(")
        out.append("(" * len(starts[i]))
        out.append(labels[order[i]])
        out.append(")" * ends[i])
    return "".join(out) + ");"


def prefix_forest_newick(t: int, bits: np.ndarray, labels: list[str], depth: int, noise: int, digits: int) -> str:
    """The same tree in the text that forest_newick makes of the SQL's clusters, whose ordinals have so many digits at least."""
    order, intervals = _prefix_runs(t, bits, depth, noise)
    long = np.concatenate(([0], np.cumsum([max(digits, len(str(x))) + 1 for x in order.tolist()])))
    sets = [(b - a + 1, int(long[b + 1] - long[a]), f"{order[a : b + 1].min():0{digits}d},", a, b) for a, b in intervals]
    kids = nested_children([order[a : b + 1] for *_, a, b in sorted(sets)], len(bits))
    label = [*labels, *[None] * (len(sets) + 1)]
    return nw.write(len(kids) - 1, kids, label, [None] * len(label))


def _prefix_runs(t: int, bits: np.ndarray, depth: int, noise: int) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """The taxa in the order of their sign strings, and the runs of it that are clusters."""
    n, width = bits.shape
    k = np.arange(depth)
    dim = np.where(_hash(t, k // 2) % 100 < 30, np.where(k % 2 == 0, k + 1, k - 1), k)
    dim = np.where(_hash(t, 1000 + k) % 100 < noise, depth + _hash(t, 2000 + k) % (width - depth), dim)
    sub = bits[:, dim]
    order = np.lexsort([np.arange(n), *[sub[:, j] for j in range(depth - 1, -1, -1)]])
    sub = sub[order]
    # depth down to which neighbours agree
    differs = sub[1:] != sub[:-1]
    common = np.where(differs.any(1), differs.argmax(1), depth).tolist() if n > 1 else []
    return order, _intervals(common, n)


def _intervals(common: list[int], n: int) -> list[tuple[int, int]]:
    """Maximal runs (first, last) of neighbours that agree to a depth of 1 or more, for every depth at which they differ in
    extent; runs of all taxa are left out."""
    found, stack = [], []  # (start, depth)
    for i in range(n):
        c = common[i] if i < n - 1 else 0
        start = i
        while stack and stack[-1][1] > c:
            start, _ = stack.pop()
            if i - start + 1 < n:
                found.append((start, i))
        if c > 0 and (not stack or stack[-1][1] < c):
            stack.append((start, c))
    return found


def prefix_trees(spark: SparkSession, bits: np.ndarray, labels: list[str], trees: int, depth: int, noise: int, partitions: int = 0) -> DataFrame:
    """(tree_id, newick) of replicates 0..trees-1; the bits of some thousand taxa are the broadcast side."""
    sent = spark.sparkContext.broadcast((bits, labels))

    def run(batches):
        for batch in batches:
            ids = np.asarray(batch.column(0))
            for at in range(0, len(ids), 256):
                part = ids[at : at + 256]
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.array([prefix_newick(int(t), *sent.value, depth, noise) for t in part])], ["tree_id", "newick"])

    frame = spark.range(0, trees, 1, partitions or spark.sparkContext.defaultParallelism)
    return frame.withColumnRenamed("id", "tree_id").mapInArrow(run, "tree_id long, newick string")


def forest_bits(spark: SparkSession, sf_dir: str, name: str) -> np.ndarray | None:
    """The bits that the SQL of emb or md5f reads, a row for each taxon; none unless the ids are 0, 1, 2 and so on."""
    if name == "emb":
        mask = F.expr("aggregate(sequence(0, 63), 0L, (a, i) -> a | shiftleft(CAST(coalesce(get(embedding, i) > 0, false) AS BIGINT), i))")
        rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("int").alias("id"), mask.alias("m")).toPandas().sort_values("id")
    else:
        rows = table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("int").alias("id"), F.unhex(F.md5(F.col("c_custkey").cast("string"))).alias("m")).toPandas().sort_values("id")
    if not np.array_equal(rows["id"].to_numpy(), np.arange(len(rows))):
        return None
    if name == "emb":
        return np.unpackbits(rows["m"].to_numpy(np.int64).astype("<i8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return np.unpackbits(np.frombuffer(b"".join(map(bytes, rows["m"])), np.uint8).reshape(-1, 16), axis=1)


def prefix_forest(spark: SparkSession, bits: np.ndarray, labels: list[str], trees: int, depth: int, noise: int, digits: int) -> DataFrame:
    """(tree_id, newick) as forest_newick makes them of the SQL's clusters, without a shuffle."""
    sent = spark.sparkContext.broadcast((np.packbits(bits, axis=1), bits.shape[1], labels))

    def run(batches):
        packed, width, names = sent.value
        mine = np.unpackbits(packed, axis=1)[:, :width]
        for batch in batches:
            for t in batch.column(0).to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array([t], pa.int64()), pa.array([prefix_forest_newick(t, mine, names, depth, noise, digits)])], ["tree_id", "newick"])

    return spark.range(0, trees, 1, min(trees, 4 * spark.sparkContext.defaultParallelism)).withColumnRenamed("id", "tree_id").mapInArrow(run, "tree_id long, newick string")


def embedding_bits(spark: SparkSession, sf_dir: str, n: int) -> tuple[np.ndarray, list[str]]:
    rows = table(spark, sf_dir, "embeddings").where(F.col("vec_id") < n).orderBy("vec_id").select("vec_id", "embedding").toPandas()
    return np.stack(rows["embedding"].to_numpy()) > 0, [f"V{i}" for i in rows["vec_id"]]


def digest_bits(spark: SparkSession, sf_dir: str, n: int) -> tuple[np.ndarray, list[str]]:
    rows = table(spark, sf_dir, "customer").where(F.col("c_custkey") < n).orderBy("c_custkey").select("c_custkey", F.md5(F.col("c_custkey").cast("string")).alias("m")).toPandas()
    raw = np.frombuffer(b"".join(bytes.fromhex(x) for x in rows["m"]), np.uint8).reshape(-1, 16)
    return np.unpackbits(raw, axis=1).astype(bool), [f"C{i}" for i in rows["c_custkey"]]
