"""Worked collections, round trips and failures of the engine on Spark."""

import json
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from cladepack import workloads as wl
from cladepack.kernels import codes
from cladepack.kernels import newick as nw
from cladepack.operators import clusters as cl
from cladepack.operators import codec as cd
from cladepack.operators import consensus as co
from cladepack.operators import hetero, measures
from cladepack.operators import newick as on

from .conftest import rows_of



def six_trees(spark):
    sets = ["DE DEF ADEF", "DE DEF BDEF", "DE DEF CDEF", "DF DEF ADEF", "EF DEF ADEF", "EF DEF BDEF"]
    out = []
    for i, text in enumerate(sets):
        a, b, c = text.split()
        inner = f"({','.join(a)})"
        mid = f"({inner},{(set(b) - set(a)).pop()})"
        top = f"({mid},{(set(c) - set(b)).pop()})"
        rest = sorted(set("ABCDEF") - set(c))
        out.append((i, f"({top},{','.join(rest)});"))
    return spark.createDataFrame(out, "tree_id long, newick string")


def test_worked_collection(spark):
    from cladepack.sources.container import textrun_lines

    lines = [r["line"] for r in textrun_lines(cd.compress(six_trees(spark), "textrun", taxa=list("ABCDEF"))).orderBy("line_no").collect()]
    assert lines == ["TAXA A:B:C:D:E:F", "NTREES 6", "NBIPARTITIONS 7", "L4K2 +:2:EB", "L3BAB +:1:D", "L3K2A +:3:ABB", "L3K3 -:0:", "L2K4 +:1:C", "ABAK3 +:2:BE", "BL2K3 +:3:ADB"]


@pytest.mark.parametrize("codec", ["packed", "packed_raw", "textrun"])
@pytest.mark.parametrize("block", [4, 65536])
def test_roundtrip(spark, codec, block):
    trees = six_trees(spark)
    packed = cd.compress(trees, codec, block)
    assert packed.count() == (2 if block == 4 else 1)
    assert cd.verify_roundtrip(trees, packed).where("ok").count() == 6


@pytest.mark.parametrize("texts", [["A;"], ["(A,B);"], ["(A,B,C);", "(A,(B,C));"], ["(A,B,C,D);"] * 3, ["((A:1.50,B:2):0.1e-3,'c d':-3)R:7;", "(('c d':1,A)lab:2,B:0);"], ["(A,(B,(C,D)));", "((A,B),(C,D));"]])
def test_small_collections(spark, texts):
    trees = spark.createDataFrame(list(enumerate(texts)), "tree_id long, newick string")
    packed = cd.compress(trees, lengths="exact", labels=True)
    assert cd.verify_roundtrip(trees, packed, True, True).where("not ok").count() == 0


def test_sizes_count_every_stored_byte(spark):
    trees = spark.createDataFrame([(3 * i, "((A:1,B:2)x:3,(C:1,D:2):4);" if i % 2 else "((A:1,C:2)y:3,(B:1,D:2):4);") for i in range(300)], "tree_id long, newick string")
    for codec in ("packed", "packed_raw", "textrun"):
        packed = cd.compress(trees, codec, 128, lengths="exact", labels=True)
        kept = [c for c, kind in packed.dtypes if kind == "binary"]
        stored = sum(len(r[c] or b"") for r in packed.collect() for c in kept)
        assert {"payload", "trees", "lengths"} <= set(kept) and measures.container_size(packed).first()["comp_bytes"] >= stored
    ids = np.array([0, 1, 2, 5, 9, 10, 70000])
    assert codes.runs_decode(codes.runs_encode(ids)).tolist() == ids.tolist() and len(codes.runs_encode(np.arange(65536))) <= 4


@pytest.mark.parametrize("how", [{"split": 7}, {"split": 64}, {"spread": False}])
def test_restore_by_pieces_and_in_place(spark, how):
    shapes = ["((A:1,B:2)x:3,(C:1,D:2):4)r:9;", "((A:1,C:2):3,(B:1,D:2)y:4);", "(((A:5,D:2):3,B:1)z:2,C:2);"]
    trees = spark.createDataFrame([(2 * i + i // 50, shapes[i * i % 3]) for i in range(200)], "tree_id long, newick string")
    packed = cd.compress(trees, "packed", 150, lengths="exact", labels=True)
    want = {tuple(r) for r in on.canonical_newick(trees, True, True).collect()}
    assert {tuple(r) for r in on.canonical_newick(cd.decompress(packed, **how), True, True).collect()} == want
    some = cd.decompress(packed, first=100, last=301, **how).select("tree_id").collect()
    assert sorted(r[0] for r in some) == sorted(r[0] for r in trees.where("tree_id between 100 and 301").collect())


def test_restore_shuffles_no_more_than_it_writes(spark):
    """Each block is decoded once: what its pieces hold is a fraction of the trees they stand for."""
    taxa = [f"t{i}" for i in range(40)]
    texts = ["(" * 39 + taxa[0] + "".join(f",{x})" for x in (taxa[k:] + taxa[:k])[1:]).replace(f",{taxa[0]})", f",{taxa[k]})") + ";" for k in range(6)]
    trees = spark.createDataFrame([(i, texts[i % 6]) for i in range(4000)], "tree_id long, newick string")
    row = cd.compress(trees).collect()[0].asDict()
    pieces = list(cd.Block(row).pieces(256, None, None))
    held = sum(len(p[c]) for p in pieces for c in ("there", "bits", "tree", "entry"))
    assert len(pieces) == 16 and sum(len(p["there"]) // 4 for p in pieces) == 4000
    assert held < 2 * sum(len(texts[i % 6]) for i in range(4000)) and sum(len(p["bits"]) for p in pieces) < 16 * 6 * 39 * 5 + 1


def test_speed_report_and_stages(spark, tmp_path):
    rows = [{"dataset": "a", "codec": "textrun", "comp_s": 3.0, "decomp_s": 8.0}, {"dataset": "a", "codec": "packed", "comp_s": 2.0, "decomp_s": 2.0}, {"dataset": "b", "codec": "packed", "comp_s": 1.0, "decomp_s": 1.0}]
    got = {(r["dataset"], r["codec"]): r for r in measures.speed_report(spark, rows).collect()}
    assert got["a", "packed"]["comp_speedup"] == 1.5 and got["a", "packed"]["decomp_pct"] == 25.0 and got["b", "packed"]["comp_speedup"] is None
    stages = measures.stage_seconds(spark, six_trees(spark), str(tmp_path))
    assert set(stages) == {"parse_s", "encode_s", "finish_s", "decode_s", "rebuild_s"} and all(v >= 0 for v in stages.values())


def test_cards_of_wide_subsets(spark):
    taxa = [f"t{i:03d}" for i in range(90)]
    text = "((" + ",".join(taxa[:70]) + ")," + ",".join(taxa[70:]) + ");"
    packed = cd.compress(spark.createDataFrame([(0, text), (1, text)], "tree_id long, newick string"))
    got = co.subset_supports(packed, taxa, taxa[:80]).collect()
    assert [(r["card"], r["n_support"]) for r in got] == [(70, 2)]


def test_empty_collection(spark):
    trees = spark.createDataFrame([], "tree_id long, newick string")
    packed = cd.compress(trees)
    assert packed.count() == 0 and cd.decompress(packed).count() == 0


def test_gaps_in_ids(spark):
    trees = six_trees(spark).withColumn("tree_id", F.col("tree_id") * 70000 + 5)
    packed = cd.compress(trees)
    assert packed.count() == 6 and cd.verify_roundtrip(trees, packed).where("ok").count() == 6
    assert [r["tree_id"] for r in cd.decompress(packed, tree_ids=[70005, 7]).collect()] == [70005]


def test_foreign_taxon(spark):
    trees = spark.createDataFrame([(0, "(A,(B,C));"), (1, "(A,(B,D));")], "tree_id long, newick string")
    with pytest.raises(Exception, match="taxon that others lack"):
        cd.compress(trees).collect()
    nodes = on.parse_newick(trees)
    assert [r["label"] for r in on.foreign_taxa(nodes, on.taxon_table(nodes)).collect()] == ["D"]


def test_damaged_payload(spark):
    packed = cd.compress(six_trees(spark)).withColumn("payload", F.expr("substring(payload, 1, 5)"))
    with pytest.raises(Exception, match="damaged"):
        cd.decompress(packed).collect()


def test_lengths_keep_every_digit(spark):
    trees = spark.createDataFrame([(0, "(A:0.12345678901234567890,(B:1e-10,C:10.0):2);")], "tree_id long, newick string")
    back = nw.parse(cd.decompress(cd.compress(trees, lengths="exact")).first()["newick"])
    assert sorted(x for x in back.length if x) == sorted(["0.12345678901234567890", "1e-10", "10.0", "2"])
    lossy = cd.decompress(cd.compress(trees, "textrun", lengths="exact"))
    assert 0 < measures.length_error(trees, lossy).first()[0] <= 5e-7


def test_parse_policies(spark):
    trees = spark.createDataFrame([(0, "(A,B);"), (1, "(A,B"), (2, None)], "tree_id long, newick string")
    assert on.parse_newick(trees, "null").select("tree_id").distinct().count() == 1
    assert on.parse_newick(trees, "quarantine").where("node_id is null").count() == 2
    with pytest.raises(Exception, match="unbalanced|empty"):
        on.parse_newick(trees).collect()
    assert on.write_newick(on.parse_newick(trees, "null")).first()["newick"] == "(A,B);"


def test_hash_methods_and_collisions(spark):
    nodes = on.parse_newick(six_trees(spark))
    taxa = on.taxon_table(nodes, "lexicographic")
    one, two = (sorted(map(tuple, cl.clusters(nodes, taxa, m).select("tree_id", "node_id", "h1", "h2", "h3").collect())) for m in ("prefix", "naive"))
    assert one == two == sorted(map(tuple, cl.hash_bottom_up(nodes, taxa).collect()))
    found = cl.clusters(nodes, taxa)
    assert cl.collisions(found).count() == 0 and cl.collisions(found, 2, 2).count() > 0
    assert cl.bipartition_table(found).count() == 7
    sides = {r["card"]: r["sign"] for r in cl.choose_side(cl.bipartition_table(found), F.lit(6)).where("n_support = 6 or n_support = 3").collect()}
    assert sides == {3: "-", 2: "+", 4: "+"}
    unrooted = cl.clusters(nodes, taxa, rooted=False)
    assert unrooted.where("kind = 'root'").count() == 0
    assert cl.collision_bound(10**6)["pair"] < 1e-17


def test_consensus_and_distances(spark):
    trees = six_trees(spark)
    packed = cd.compress(trees, taxa=list("ABCDEF"))
    supports, entries = co.cluster_supports(packed), co.container_entries(packed)
    strict = co.consensus_tree(co.consensus_clusters(supports, 6, "strict"), list("ABCDEF"))
    assert nw.canonical(nw.parse(strict)) == "(A,B,C,(D,E,F));"
    assert co.consensus_clusters(supports, 6, "majority").count() == 1
    assert co.consensus_clusters(supports, 6, "majority", 0.4).count() == 3
    greedy = [codes.unpack_bits(bytes(r["bits"]), 6) for r in co.consensus_clusters(supports, 6, "greedy").collect()]
    from cladepack.kernels import trees as tk

    assert tk.is_laminar(np.array(greedy)) and len(greedy) == 3
    rf = {(r["t1"], r["t2"]): r["rf"] for r in co.rf_matrix(entries, 6).collect()}
    assert len(rf) == 15 and rf[0, 1] == 2 and rf[0, 5] == 4
    assert {r["tree_id"] for r in co.trees_with(entries, co.bits_of(list("ABCDEF"), ["E", "F"])).collect()} == {4, 5}
    assert co.clusters_of(entries, 3).count() == 3


def test_merge(spark):
    trees = six_trees(spark)
    one, two = cd.compress(trees.where("tree_id < 4"), block=4), cd.compress(trees.where("tree_id >= 4"), block=4)
    assert cd.decompress(cd.merge(one, two)).count() == 6


def test_data_source(spark, tmp_path):
    from cladepack.sources import container as cs

    cs.register(spark)
    trees = six_trees(spark)
    cs.write_container(cd.compress(trees, block=2), str(tmp_path / "c"))
    read = spark.read.format("cladepack").load(str(tmp_path / "c"))
    assert read.count() == 6
    assert [r["tree_id"] for r in read.where("tree_id >= 3 and tree_id < 5").orderBy("tree_id").collect()] == [3, 4]
    cs.write_newick_text(trees, str(tmp_path / "n"))
    back = cs.read_newick(spark, str(tmp_path / "n"))
    assert on.distinct_topologies(back).count() == on.distinct_topologies(trees).count() == 6


def test_sql_functions(spark):
    from cladepack.functions import sqlapi

    sqlapi.register(spark)
    row = spark.sql("SELECT hex(packed_bits_encode(X'AA')) a, packed_ids_decode(packed_ids_encode(array(3, 5, 900)), 3) b, newick_valid('(A,B);') c, canonical_newick('(B,A);') d, CAST(inflate(own_deflate(CAST('aaaaaaaaaa' AS BINARY))) AS STRING) e").first()
    assert tuple(row) == ("02AA00", [3, 5, 900], True, "(A,B);", "aaaaaaaaaa")
    assert spark.sql("SELECT * FROM newick_nodes('((A,B),C);')").count() == 5
    assert spark.sql("SELECT sum(CASE WHEN literal >= 0 THEN 1 ELSE length END) FROM lz77_tokens(CAST('abcabcabc' AS BINARY))").first()[0] == 9


def test_heterogeneous_sets(spark, sf):
    trees = spark.createDataFrame([(0, "(A,(B,C));"), (1, "((C,D),E);"), (2, "(A,(B,C));")], "tree_id long, newick string")
    taxa = hetero.union_taxa(trees)
    packed = hetero.compress_hetero(trees, taxa)
    assert packed.select("mask").distinct().count() == 2
    back = on.canonical_newick(hetero.decompress_hetero(packed, taxa))
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, on.canonical_newick(trees).collect()))


@pytest.mark.parametrize("name", ["forest_nat_clusters", "forest_emb_clusters", "roundtrip_nat", "majority_consensus_nat", "rebuild_window", "textrun_codes", "packed_ids_hex", "consensus_subset", "stream_evt_clusters", "six_digit_lengths", "length_error_by_codec", "collisions_small_primes", "crossing_clusters", "accuracy_damaged", "textrun_payload_bytes", "textrun_codes_emb"])
def test_against_sql(spark, sf, duck, name):
    got = wl.queries()[name](spark, sf).toPandas()
    assert rows_of(got) == rows_of(duck.sql(wl.oracle_sql()[name]).df())


def test_plans_have_no_cartesian(spark, sf):
    for name in ("forest_nat_clusters", "rebuild_window", "trees_with_cluster"):
        plan = wl.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan, name


def test_orderings_of_sizes(spark, sf):
    rows = {r["codec"]: r for r in wl.workload_query("w02", 60)(spark, sf).collect()}
    assert rows["packed"]["comp_bytes"] < rows["packed_raw"]["comp_bytes"] < rows["textrun"]["comp_bytes"]
    assert all(r["ok_share"] == 1.0 for r in rows.values())


def test_entry(spark):
    import __spark_entry__ as e

    out = e.entry(spark)
    assert out.where("not ok").count() == 0 and out.count() == 80
    assert set(e.oracle_sql()) <= set(e.queries())


def test_running_support_processor():
    """State update of the running table, without a store."""
    import pandas as pd

    from cladepack.streaming.ingest import RunningSupport

    class State:
        value = None

        def exists(self):
            return self.value is not None

        def get(self):
            return self.value

        def update(self, v):
            self.value = v

    p = RunningSupport()
    p.count = State()
    list(p.handleInputRows(("x",), iter([pd.DataFrame({"a": [1, 2]})]), None))
    out = next(iter(p.handleInputRows(("x",), iter([pd.DataFrame({"a": [1]})]), None)))
    assert out["n_support"].tolist() == [3]


def test_container_fields(spark):
    row = cd.compress(six_trees(spark), lengths="none").first()
    assert row["n_bip"] == 7 and row["n_trees"] == 6 and zlib.crc32(row["payload"]) == row["crc"] and json.dumps(row["taxa"])


def test_deflate_queries_take_whole_texts(spark, duck, tmp_path):
    page = "".join(f"<p>{i * i} line {i}</p>\n" for i in range(2500)) + "é" * 3000
    spark.createDataFrame([(1, "u", page), (2, "u", "")], "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    spark.createDataFrame([(1, page[:9000])], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {r["page_id"]: r for r in wl.queries()["lz77_roundtrip_pages"](spark, str(tmp_path)).collect()}
    assert got[1]["n_bytes"] == len(page.encode()) > 2 * 32768 and got[1]["same"] and got[2]["n_bytes"] == 0
    modes = {(r["asked"], r["mode"]): r["bytes"] for r in wl.queries()["deflate_block_modes"](spark, str(tmp_path)).collect()}
    assert modes["stored", "stored"] == len(page[:9000])
    assert wl.queries()["deflate_own_vs_zlib"](spark, str(tmp_path)).where("own_then_standard and standard_then_own").count() == 1


def test_pages_with_many_leaves_and_with_none_have_rows(spark, tmp_path):
    big = "<ul>" + "".join(f"<li><b>{i}</b></li>" for i in range(450)) + "</ul><p>x</p>"
    spark.createDataFrame([(1, "u", big), (2, "u", "no elements"), (3, "u", "<p>a</p><p>b</p>"), (4, "u", None)], "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    assert {r["tree_id"]: r["ok"] for r in wl.hetero_pages(spark, str(tmp_path)).collect()} == {1: True, 2: None, 3: True, 4: None}


def test_members_longer_than_their_width_are_whole(spark):
    got = spark.sql(f"SELECT {wl.SPARK.members('x', 4)} AS m FROM VALUES (12345L), (7L), (1234L), (10000L) AS t(x)").first()["m"]
    assert got == "0007,1234,10000,12345"


def test_workloads_report_their_taxa_and_are_all_registered(spark, sf):
    rows = wl.workload_query("w07", 3)(spark, sf).collect()
    assert {r["n_taxa"] for r in rows} == {spark.read.parquet(f"{sf}/customer.parquet").count()} and {r["ok_share"] for r in rows} == {1.0}
    assert {f"{name}_codecs" for name in wl.WORKLOADS} <= set(wl.queries())


def test_whole_forests_take_all_rows(spark, sf, duck):
    from cladepack.plans import forests as fo

    n = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    noise = next(w for w in wl.WORKLOADS.values() if w[0] >= n)[1]
    want = duck.sql(f"WITH {fo.emb_sql(wl.DUCK, n, 3, wl.preset_depth(n), noise)} SELECT tree_id, members, card FROM emb").df()
    for packed in (False, True):
        assert rows_of(wl.whole_clusters("emb", packed, 3)(spark, sf).toPandas()) == rows_of(want)
    assert {"forest_emb_all_clusters", "forest_md5_all_clusters", "roundtrip_emb_all", "roundtrip_md5_all"} <= set(wl.queries())


def test_parsing_many_taxa_holds_few_rows_unpacked():
    import tracemalloc

    from cladepack.plans import forests as fo

    n = 4000
    bits = np.random.default_rng(1).integers(0, 2, (n, 64)).astype(np.uint8)
    labels = [f"C{i}" for i in range(n)]
    texts = [fo.prefix_newick(t, bits, labels, 20, 2) for t in range(12)]
    take = cd.Extractor(labels, 12, False)
    tracemalloc.start()
    n_rows = sum(1 for _ in take(np.arange(12), texts))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert n_rows > 10000 and peak < 60e6


def test_roundtrip_blocks_are_restorable(spark):
    assert cd.restorable_block(25) == cd.BLOCK_TREES and cd.restorable_block(15000) < 10 and cd.restorable_block(10**6) == 1


def test_prefix_forest_is_the_sql_forest(spark, sf):
    from cladepack.plans import forests as fo

    for name in ("emb", "md5f"):
        trees, labels = wl.trees_of(spark, sf, name)
        want = fo.forest_newick(wl.forest(spark, sf, name).select("tree_id", "members"), labels)
        assert sorted(trees.collect()) == sorted(want.collect())
        assert "Exchange" not in trees._jdf.queryExecution().executedPlan().toString()


def test_text_bits_are_decoded_whole():
    import tracemalloc

    n = 1_000_000
    bits = codes.pack_bits(np.arange(5, n, 70_001), n)
    data = f"TAXA\nNTREES 1\nNBIPARTITIONS 1\n{codes.textrun_bits_encode(codes.bit_text(bits, n))} +:1:A\n".encode()
    tracemalloc.start()
    got = list(cd.decode_payload(data, n, 1, "textrun"))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert [(b, s, i.tolist()) for b, s, i in got] == [(bits, "+", [0])] and peak < 6e6


def test_laminar_sets_as_by_window(spark, sf):
    made = wl.forest(spark, sf, "nat").select(F.expr("tree_id div 2").alias("tree_id"), "members", "card").distinct()
    rows = made.select("tree_id", F.col("members").alias("cluster"), "card", F.explode(F.split("members", ",")).alias("taxon"))
    want = sorted(map(tuple, co.check_laminar(rows).collect()))
    assert want and sorted(map(tuple, co.check_laminar_sets(made).collect())) == want
    plan = wl.laminar_violations(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in plan


def test_ablation_streams_are_tasks_of_their_own(spark, sf):
    import zlib

    got = wl.ablation_grid(spark, sf)
    assert "Coalesce" not in got._jdf.queryExecution().executedPlan().toString()
    trees, labels = wl.trees_of(spark, sf, "emb")
    rows = cd.container_entries(cd.compress(trees, taxa=labels)).select("bits", "support").orderBy("bits").collect()
    want = set()
    for k in wl.ABLATION:
        pack, raw, size = zlib.compressobj(6, zlib.DEFLATED, -15), 0, 0
        for r in rows:
            one, two, sign, listed = cd.encode_one(bytes(r["bits"]), len(labels), np.array(r["support"], np.int64), 100, *k)
            entry = one + codes.varint(2 * len(listed) + (sign == "-")) + two
            raw, size = raw + len(entry), size + len(pack.compress(entry))
        want.add((*k, raw, size + len(pack.flush())))
    assert set(map(tuple, got.collect())) == want


def test_subtree_sizes_shuffle_digests_not_texts(spark):
    plan = cd.subtree_dictionary_size(six_trees(spark))._jdf.queryExecution().executedPlan().toString()
    assert "subtree#" not in plan


def test_clusters_of_many_taxa_take_the_space_of_their_members():
    from cladepack.plans import forests as fo

    n = 4000
    bits = np.random.default_rng(2).integers(0, 2, (n, 64)).astype(np.uint8)
    labels = [f"C{i}" for i in range(n)]
    rows = list(cd.Extractor(labels, 1, False)(np.arange(2), [fo.prefix_newick(t, bits, labels, 20, 2) for t in range(2)]))
    assert sum(len(r[1]) for r in rows) < len(rows) * n // 8 // 4
    row, at = codes.members_of([r[1] for r in rows])
    assert len(at) and all(1 < c < n for c in np.bincount(row)[[bool(r[1]) for r in rows]])


def test_trees_that_are_blocks_are_packed_and_restored_in_place(spark):
    import tracemalloc

    from cladepack.plans import forests as fo

    n = 8000
    bits = np.random.default_rng(3).integers(0, 2, (n, 64)).astype(np.uint8)
    labels = [f"C{i}" for i in range(n)]
    trees = fo.prefix_trees(spark, bits, labels, 2, 20, 2)
    packed = cd.compress(trees, block=1, taxa=labels)
    for plan in (packed, cd.decompress(packed, spread=False)):
        assert "Exchange" not in plan._jdf.queryExecution().executedPlan().toString()
    assert cd.verify_roundtrip(trees, packed).where("ok").count() == 2
    row = packed.first().asDict()
    tracemalloc.start()
    block = cd.Block(row)
    held = tracemalloc.get_traced_memory()[0]
    tracemalloc.stop()
    assert held < len(block.keys) * n // 8


def test_codes_of_clusters_are_made_in_parallel(spark, sf):
    """One meeting of the clusters; no task takes all of them."""
    plan = wl.queries()["packed_bits_hex"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "hashpartitioning(block" in plan and "key" in plan.split("hashpartitioning(block")[1][:20]
