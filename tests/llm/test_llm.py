"""The text operators against brute force, exact round trips and held-out accuracy, and on odd tables."""

import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from cladepack.llm import components as C
from cladepack.llm import decontam, exact_dedup, html_extract, langid, line_dedup, mixing, ngram_join, pii, quality_fm, queries, secrets
from cladepack.llm.common import Scratch, lookup, shingle_sets, word_hashes

from ..conftest import rows_of

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, lang, src, None) for i, t, lang, src in rows], SCHEMA)


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls everywhere, empty and long texts, ties, repeated rows, and a column whose name the operators use themselves."""
    long = " ".join(f"w{i}" for i in range(30000))
    rows = [(1, None, None, None), (2, "", "en", "a"), (3, " \n\t ", "en", "a"), (4, "one two three", "en", "b"), (5, "ONE two three", None, "b"), (6, long, "en", "a"), (7, long + " x", "en", None), (8, "héé " * 5, "fr", "c"), (8, "héé " * 5, "fr", "c"), (None, "no id at all", "en", "a")]
    return docs_of(spark, rows).withColumn("m", F.lit("clash")).withColumn("tile", F.lit(1)).withColumn("size", F.lit("x"))


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def union_find(ids, links):
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def shingles(text, n):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set()


# --- shared parts -------------------------------------------------------------------------------------------------


def test_word_hashes_follow_the_words():
    texts = ["A b\tc", "", None, "é É x" * 3, "a" * 1_300_000 + " b", " lead trail ", "a b c"]
    words, off = word_hashes(pa.array(texts))
    split = [(t or "").encode().lower().split() for t in texts]
    assert np.diff(off).tolist() == [len(s) for s in split]
    flat = [w for s in split for w in s]
    assert len(set(zip(flat, words.tolist()))) == len(set(flat)) == len(set(words.tolist()))
    sets = shingle_sets(words, off, 2)
    assert [len(s) for s in sets] == [len(shingles(t, 2)) for t in texts]


@pytest.mark.parametrize("task_links", [7, 10**6])
def test_components(spark, task_links):
    rng = random.Random(1)
    links = [(rng.randrange(60), rng.randrange(60)) for _ in range(40)] + [(i, i + 1) for i in range(100, 130)]
    got = {r["node"]: r["component"] for r in C.connected_components(Scratch(spark, "t"), spark.createDataFrame(links, "a long, b long"), task_links=task_links).collect()}
    want = union_find({x for p in links for x in p}, links)
    assert got == {x: want[x] for p in links if p[0] != p[1] for x in p}


def test_bitmap_bound_never_cuts_a_link():
    rng = np.random.default_rng(0)
    for _ in range(300):
        base = rng.integers(0, 2**63, 400, dtype=np.uint64)
        a, b = np.unique(rng.choice(base, int(rng.integers(5, 300)))), np.unique(rng.choice(base, int(rng.integers(5, 300))))
        x, y = (np.frombuffer(C.bitmap(s), np.uint64) for s in (a, b))
        w = min(len(x), len(y))
        assert C.overlap_bound(len(a), C.fold(x, w), len(b), C.fold(y, w)) >= len(np.intersect1d(a, b))


def test_lookup_with_a_hot_group(spark):
    rows = spark.range(5000).select((F.col("id") % 7 * (F.col("id") % 2)).alias("k"), "id")
    groups = rows.groupBy("k").agg(F.count("*").alias("n"))
    out = lookup(rows, groups, ["k"], "n", 5000)
    assert out.count() == 5000 and out.where("n is null").count() == 0


# --- 1 ------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("kind", ["golden", "corput"])
def test_mix(spark, sf, kind):
    out = mixing.mix_sources(spark.read.parquet(f"{sf}/documents.parquet"), kind=kind).toPandas()
    assert (out["taken"] <= 2 * out["size"]).all()
    per = out.groupby("source").agg(t=("target", "first"), s=("source_size", "first"), got=("taken", "sum"), size=("size", "sum"))
    assert (per["s"] == per["size"]).all() and (abs(per["got"] - per["t"]) <= 1).all() and (per["t"] <= 2 * per["s"]).all()
    assert abs(per["t"].sum() - 1.5 * out["size"].sum()) < 1e-6 * out["size"].sum()


def test_mix_follows_its_schedule(spark, sf):
    """The slots of the query's own output: other points give other slots, and every stretch of the schedule holds the
    sources near their shares, as points in random order do not."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    golden, corput = (mixing.mix_sources(docs, kind=k).toPandas().sort_values("doc_id").reset_index(drop=True) for k in ("golden", "corput"))
    assert (golden["taken"] == corput["taken"]).all() and (golden["first_slot"] != corput["first_slot"]).mean() > 0.5
    assert ((golden["first_slot"] < 0) == (golden["taken"] == 0)).all() and ((golden["n_pieces"] > 0) == (golden["taken"] > 0)).all()
    sizes = golden.groupby("source", dropna=False).agg(size=("size", "sum"), target=("target", "first"))
    block = max(1, min(mixing.MOST_BLOCK, int(sizes["size"].sum()) // (256 * len(sizes))))
    targets = spark.createDataFrame([(i + 1, float(t)) for i, t in enumerate(sizes["target"])], "source_id long, target double")
    plan = mixing.schedule(targets, block, Scratch(spark, "t")).toPandas().sort_values("slot")
    share, n = sizes["target"].to_numpy() / sizes["target"].sum(), len(plan)
    worst = 0.0
    for stop in range(20, int(0.95 * n), 17):
        got = np.bincount(plan["source_id"][:stop], minlength=len(share) + 1)[1:]
        worst = max(worst, abs(got - stop * share).max())
    assert worst <= 1.5 * np.log2(n) and worst < 0.5 * np.sqrt(n)


def test_mix_breaks_ties_by_size(spark):
    rows = [(1, "a " * k, "en", "s") for k in (5, 3, 9)] + [(i, "b c", "en", "t") for i in range(2, 30)]
    one, two = (mixing.mix_sources(docs_of(spark, r).repartition(p)).select("doc_id", "size", "taken", "first_slot").collect() for r, p in ((rows, 3), (rows[::-1], 7)))
    assert sorted(map(str, one)) == sorted(map(str, two))


def test_mix_targets_share_the_excess(spark):
    sizes = spark.createDataFrame([("a", 10), ("b", 100), ("c", 100), (None, 50)], "source string, source_size long")
    got = {r["source"]: r["target"] for r in mixing.source_targets(sizes, [3, 1, 2], 1.5).collect()}
    # 390 to share: a stops at 20; b and c take 1 and 2 parts of what is left, the last source 3
    left = 390 - 20
    want = {"a": 20.0, None: 100.0}
    rest = left - 100
    want |= {"b": rest / 3, "c": rest * 2 / 3}
    assert got == pytest.approx(want)


def test_schedule_is_even(spark):
    targets = spark.createDataFrame([(1, 6000.0), (2, 3000.0), (3, 1000.0)], "source_id long, target double")
    plan = mixing.schedule(targets, 10, Scratch(spark, "t")).orderBy("slot").toPandas()
    assert plan.groupby("source_id")["rank"].count().to_dict() == {1: 600, 2: 300, 3: 100}
    assert plan.sort_values("slot").groupby("source_id")["rank"].apply(lambda r: (r.diff().dropna() == 1).all()).all()
    first = plan[plan["slot"] < 500].groupby("source_id")["slot"].count()
    assert abs(first[1] - 300) <= 6 and abs(first[2] - 150) <= 6 and abs(first[3] - 50) <= 6


def test_mix_odd(spark, odd, none):
    out = mixing.mix_sources(odd).toPandas()
    assert len(out) == 10 and out["size"].tolist().count(0) == 3 and (out["taken"] <= 2 * out["size"]).all()
    assert mixing.mix_sources(none).count() == 0


# --- 2 ------------------------------------------------------------------------------------------------------------


def test_feistel_is_a_permutation():
    f = pii.Feistel(b"k")
    for size in (1, 2, 10, 1000, 4097):
        image = [f.permute("t", x, size) for x in range(size)]
        assert sorted(image) == list(range(size))
        assert [f.permute("t", y, size, True) for y in image] == list(range(size))
    assert [f.permute("t", x, 1000) for x in range(50)] != [pii.Feistel(b"other").permute("t", x, 1000) for x in range(50)]


VALUES = {"card": "4539 1488 0343 6467", "phone": "+1 (743) 555-3824", "ip": "227.5.221.1", "ssn": "123-45-6789", "date": "2023-02-28", "iban": "DE89 3704 0044 0532 0130 00", "email": "jane.doe@mail.example.com"}


@pytest.mark.parametrize("kind,value", VALUES.items())
def test_pseudonyms_keep_the_format(kind, value):
    f = pii.Feistel(b"k")
    text, spans = pii.pseudonymise(f"see {value}, or {value}.", f)
    assert [s[0] for s in spans] == [kind] * 2 and spans[0][3] == spans[1][3] != value
    if kind != "ip":
        assert re.sub(r"[A-Za-z]", "a", re.sub(r"\d", "9", spans[0][3])) == re.sub(r"[A-Za-z]", "a", re.sub(r"\d", "9", value))
    assert pii.pseudonymise(text, f, True)[0] == f"see {value}, or {value}."


def test_pseudonyms_stay_valid_and_linked():
    f = pii.Feistel(b"k")
    new = pii.pseudonym(f, "card", "4539148803436467")
    assert pii.luhn_digit(new[:-1]) == new[-1]
    assert pii.pseudonym(f, "card", "4539 1488 0343 6467").replace(" ", "") == new
    for kind, value in (("card", "4539148803436468"), ("date", "2023-02-30"), ("ip", "300.1.1.1"), ("ssn", "666-45-6789"), ("ssn", "123-00-6789"), ("iban", "DE88370400440532013000"), ("phone", "+0170 555 1234")):
        assert pii.pseudonym(f, kind, value) is None
    for day in ("3/4/1999", "28.02.2020", "12-31-2011"):
        assert pii.pseudonym(f, "date", pii.pseudonym(f, "date", day), True) == day


def test_spellings_of_a_value_share_one_pseudonym():
    """Against a table made by brute force: one pseudonym for each value, whatever its spelling."""
    rng, f = random.Random(4), pii.Feistel(b"k")
    of_day = {}
    for _ in range(150):
        y, m, d = rng.randrange(1900, 2100), rng.randrange(1, 13), rng.randrange(1, 29)
        spelled = [f"{y}-{m:02d}-{d:02d}", f"{y}/{m:02d}/{d:02d}", f"{d:02d}.{m:02d}.{y}", f"{d}/{m}/{y}"] + [f"{m:02d}-{d:02d}-{y}", f"{m}/{d}/{y}"] * (d > 12)
        got = set()
        for text in spelled:
            new = pii.pseudonym(f, "date", text)
            assert len(new) == len(text) and pii.pseudonym(f, "date", new, True) == text
            a, b, c = (int(x) for x in re.split(r"[-/.]", new))
            got.add((a, b, c) if a > 31 else (c, b, a) if b <= 12 else (c, a, b))
        assert len(got) == 1
        of_day[y, m, d] = got.pop()
    assert len(set(of_day.values())) == len(of_day)
    phones = [["+4917012345678", "+49 170 1234 5678", "+49-170-1234-5678"], ["+1 (743) 555-3824", "+17435553824", "+1 743 555 3824"], ["+353 861 234 567", "+353861234567"], ["(743) 555-3824", "743-555-3824"]]
    for spelled in phones:
        new = ["".join(filter(str.isdigit, pii.pseudonym(f, "phone", x))) for x in spelled]
        code = {"+4": 2, "+1": 1, "+3": 3}.get(spelled[0][:2], 0)
        assert len(set(new)) == 1 and new[0][:code] == spelled[0][1 : 1 + code]
        assert [pii.pseudonym(f, "phone", pii.pseudonym(f, "phone", x), True) for x in spelled] == spelled
    for kind, one, two in (("iban", "DE89370400440532013000", "DE89 3704 0044 0532 0130 00"), ("card", "4539-1488-0343-6467", "4539148803436467"), ("ssn", "123-45-6789", "123-45-6789")):
        x, y = pii.pseudonym(f, kind, one), pii.pseudonym(f, kind, two)
        assert re.sub(r"\W", "", x) == re.sub(r"\W", "", y)
    ssn = pii.pseudonym(f, "ssn", "123-45-6789")
    assert ssn[:3] not in ("000", "666") and ssn[0] != "9" and ssn[4:6] != "00" and ssn[7:] != "0000"


def test_pii_query_against_brute_force(spark, sf):
    """Every row of the query, by a plain loop over its text: valid values are replaced, all else stays."""
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    f = pii.Feistel(__import__("hmac").new(queries.EXAMPLE_KEY, b"format-preserving", hashlib.sha256).digest())
    for r in queries.op2_pii_pseudonyms(spark, sf).collect():
        text = docs[r["doc_id"]]
        want, at, spans = "", 0, []
        for m in pii._SCAN.finditer(text or ""):
            new = None if "\n" in m[0] else pii.pseudonym(f, m.lastgroup, m[0])
            if new is not None:
                want += text[at : m.start()] + new
                at = m.end()
                spans.append(f"{m.lastgroup}:{m.start()}:{m.end()}")
        assert (r["text"] or "") == want + (text or "")[at:] and r["spans"] == ",".join(spans) and r["n_replaced"] == len(spans)


def test_pii_in_a_long_text():
    text = "x " * 2_000_000 + "card 4539148803436467 " + "y" * 1_000_000
    assert pii.pseudonymise(text, pii.Feistel(b"k"))[1][0][:2] == ("card", 4_000_005)


def test_pii_table(spark, sf, odd, none):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    new = pii.replace_pii(docs, b"key")
    back = pii.replace_pii(new, b"key", back=True).select("doc_id", F.col("text").alias("back"))
    assert new.where("size(spans) > 0").count() > 3
    assert docs.join(back, "doc_id").where("not (text <=> back)").count() == 0
    assert pii.replace_pii(odd, b"k").count() == 10 and pii.replace_pii(none, b"k").count() == 0


# --- 3 ------------------------------------------------------------------------------------------------------------


def near_texts(rng, groups, copies):
    out = []
    for _ in range(groups):
        base = [f"v{rng.randrange(4000)}" for _ in range(rng.randrange(2, 160))]
        for _ in range(copies):
            w = list(base)
            for _ in range(rng.randrange(0, 6)):
                w[rng.randrange(len(w))] = f"z{rng.randrange(10**6)}"
            out.append(" ".join(w))
    return out


@pytest.mark.parametrize("n,num,den", [(4, 85, 100), (5, 4, 5), (1, 1, 2)])
def test_ngram_join_loses_no_link(spark, monkeypatch, n, num, den):
    monkeypatch.setattr(C, "BLOCK", 5)
    monkeypatch.setattr(C, "SMALL", 3)
    texts = near_texts(random.Random(n), 12, 14) + ["", None, "a", "A", "a b", "one two three four"]
    docs = docs_of(spark, [(i, t, "en", "s") for i, t in enumerate(texts)])
    got = {r["doc_id"]: r["component_id"] for r in ngram_join.ngram_jaccard_components(docs, n, num, den).collect()}
    sets = [shingles(t, n) for t in texts]
    links = [(i, j) for i in range(len(texts)) for j in range(i) if sets[i] and sets[j] and den * len(sets[i] & sets[j]) >= num * len(sets[i] | sets[j])]
    assert got == union_find(range(len(texts)), links)


def test_tiles_are_shared_by_linked_sets():
    rng = np.random.default_rng(5)
    for num, den in ((85, 100), (4, 5), (1, 2)):
        for _ in range(400):
            n = int(rng.integers(1, 120))
            a = rng.integers(0, 2**64, n, dtype=np.uint64)
            b = np.concatenate([a, rng.integers(0, 2**64, int(rng.integers(0, max(1, n // 4) + 1)), dtype=np.uint64)])
            b = np.delete(b, rng.integers(0, len(b), int(rng.integers(0, max(1, n // 5) + 1))))
            a, b = np.unique(a), np.unique(b)
            if len(a) and len(b) and not np.array_equal(a, b) and ngram_join.linked(a, b, num, den):
                assert np.intersect1d(ngram_join.tile_keys(a, num, den)[0], ngram_join.tile_keys(b, num, den)[0]).size


def test_tile_keys_are_short_and_needs_count_distinct_ones(monkeypatch):
    s = np.unique(np.random.default_rng(6).integers(0, 2**64, 4000, dtype=np.uint64))
    keys, _ = ngram_join.tile_keys(s, 4, 5)
    assert len(keys) > 300 and (keys < 1 << 48).all()
    monkeypatch.setattr(ngram_join, "_TILE", np.uint64(1))  # all keys of a band meet
    assert ngram_join.tile_keys(s, 4, 5)[1] in ([1, 0], [0, 1], [1, 1])


def test_ngram_join_odd(spark, odd, none):
    got = ngram_join.ngram_jaccard_components(odd, 4, 85, 100).toPandas()
    by = got.set_index("doc_id")["component_id"]
    assert len(got) == 10 and by[7] == 6 and by[5] == 4 and by[1] == 1 and got["n_shingles"].tolist().count(0) == 3
    assert ngram_join.ngram_jaccard_components(none).count() == 0
    assert ngram_join.keep_one_of_each(none).count() == 0


# --- 4 ------------------------------------------------------------------------------------------------------------


def test_line_dedup_against_brute_force(spark):
    rng = random.Random(3)
    base = ["".join(rng.choice("abcdefgh ") for _ in range(rng.randrange(60, 140))) for _ in range(25)]
    lines = []
    for _ in range(160):
        line = list(rng.choice(base))
        for _ in range(rng.randrange(0, 2)):
            line[rng.randrange(len(line))] = rng.choice("xyz")
        lines.append("".join(line))
    texts = ["\n".join(lines[i : i + 4] + ["", "ok"]) for i in range(0, len(lines), 4)]
    got = {r["doc_id"]: (r["n_lines"], r["dropped"]) for r in line_dedup.duplicate_lines(docs_of(spark, [(i, t, None, None) for i, t in enumerate(texts)])).collect()}
    spots = [(i, j, line) for i, t in enumerate(texts) for j, line in enumerate(t.split("\n")) if line.strip()]
    uniq = sorted({s[2] for s in spots})
    sets = {u: line_dedup.shingles(u) for u in uniq}
    links = [(a, b) for a in uniq for b in uniq if a < b and sets[a] and sets[b] and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])]
    comp = union_find(uniq, links)
    first, want = {}, {i: [] for i in range(len(texts))}
    for i, j, line in spots:
        if comp[line] in first:
            want[i].append(j)
        first.setdefault(comp[line], (i, j))
    missed = sum(want[i] != got[i][1] for i in want)
    assert all(set(got[i][1]) <= set(want[i]) for i in want) and missed <= 1


def test_line_dedup_odd(spark, odd, none):
    got = line_dedup.duplicate_lines(odd).toPandas().set_index("doc_id")
    assert got.loc[1, "n_lines"] == 0 and len(got) == 10 and sorted(got.loc[8, "n_dropped"]) == [0, 1]
    assert line_dedup.duplicate_lines(none).count() == 0
    docs = docs_of(spark, [(1, "same line here\n\nother", "en", "a"), (2, "x\nsame line here", "en", "a"), (3, None, "en", "a")])
    assert {r["doc_id"]: r["text"] for r in line_dedup.drop_duplicate_lines(docs).collect()} == {1: "same line here\n\nother", 2: "x", 3: None}
    clash = line_dedup.drop_duplicate_lines(odd.withColumn("dropped", F.lit("x")).withColumn("cut", F.lit(1)).withColumn("row_number", F.lit(2)))
    assert clash.columns == [*odd.columns, "dropped", "cut", "row_number"] and clash.count() == 10
    assert line_dedup.drop_duplicate_lines(none).count() == 0


# --- 5 ------------------------------------------------------------------------------------------------------------


def brute_contamination(text, items, window):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    w, hit, found = words(text), set(), set()
    for item, body in items:
        b = words(body)
        k = min(window, len(b))
        for i in range(len(b) - k + 1 if b else 0):
            for j in range(len(w) - k + 1):
                if w[j : j + k] == b[i : i + k]:
                    hit |= set(range(j, j + k))
                    found.add(str(item))
    return len(w), len(hit), sorted(found)


@pytest.mark.parametrize("most", [500_000, 0])
def test_decontaminate_against_brute_force(spark, monkeypatch, most):
    monkeypatch.setattr(decontam, "MOST_TOKENS", most)
    rng = random.Random(2)
    word = lambda: rng.choice(["the", "a", "of", "Éa", "éa", "K9", "x"]) + rng.choice(["", "", "b", "ü"])
    items = [(i, " ".join(word() for _ in range(n))) for i, n in enumerate([1, 2, 5, 13, 14, 30, 0, 13])] + [(10, None), (11, "same words here " * 6), (12, "same words here " * 6)]
    texts = [" ".join(word() for _ in range(rng.randrange(0, 60))) for _ in range(60)]
    for i in range(0, 60, 3):
        texts[i] += ", " + rng.choice([b for _, b in items if b]).upper().replace("É", "É") + "! " + texts[i + 1]
    texts += [None, "", "...", "same WORDS here " * 9]
    docs = docs_of(spark, [(i, t, None, None) for i, t in enumerate(texts)])
    bench = spark.createDataFrame(items, "item_id long, text string")
    for window in (13, 3):
        got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["item_ids"]) for r in decontam.decontaminate(docs, bench, window).collect()}
        assert got == {i: brute_contamination(t, items, window) for i, t in enumerate(texts)}


def test_decontaminate_is_native_and_takes_odd_tables(spark, odd, none):
    bench = spark.createDataFrame([(1, "one two three")], "item_id long, text string")
    out = decontam.decontaminate(odd, bench)
    assert not re.search("Python|Pandas|Arrow", out._jdf.queryExecution().executedPlan().toString())
    by = out.toPandas().set_index("doc_id")
    assert by.loc[4, "contaminated"] and by.loc[5, "n_hit"] == 3 and by.loc[1, "n_words"] == 0
    assert decontam.decontaminate(none, bench).count() == 0
    empty = spark.createDataFrame([], "item_id long, text string")
    assert decontam.decontaminate(odd, empty).where("n_hit > 0").count() == 0


def test_decontaminate_words_with_capitals_and_rows_with_equal_ids(spark):
    rows = [(1, "Москва"), (2, "москва"), (3, "ÉCOLE x"), (4, "one two three"), (4, "other words"), (None, "one two three"), (None, "more words"), (5, "école")]
    docs = docs_of(spark, [(i, t, None, None) for i, t in rows])
    bench = spark.createDataFrame([(1, "Москва"), (2, "москва"), (3, "ÉCOLE"), (4, "one two three")], "item_id long, text string")
    got = sorted(str((r["doc_id"], r["n_words"], r["n_hit"], r["item_ids"])) for r in decontam.decontaminate(docs, bench).collect())
    assert got == sorted(str((i, *brute_contamination(t, [(r["item_id"], r["text"]) for r in bench.collect()], 13))) for i, t in rows)
    assert sorted(r["text"] for r in decontam.drop_contaminated(docs, bench).collect()) == ["more words", "other words", "école"]


# --- 6 ------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("n", [0, 1, 2, 3, 10, 1000, 30000])
def test_fuse_filter(n):
    rng = np.random.default_rng(n)
    keys = rng.integers(-(2**63), 2**63, n)
    f = exact_dedup.FuseFilter.unpack(exact_dedup.FuseFilter.build(keys).pack())
    assert f.contains(keys).all()
    others = rng.integers(-(2**63), 2**63, 20000)
    assert f.contains(others).mean() < 0.01 or n < 3
    if n > 20000:
        assert len(f.prints) < 1.35 * n


def test_snapshot_screens(spark):
    keys = spark.range(3000).select((F.col("id") * 7919).alias("key"), F.lit(1).cast("long").alias("n_bytes"), F.sha2(F.col("id").cast("string"), 256).cast("binary").alias("sha"), F.col("id").alias("keep"), F.lit(1).cast("long").alias("group_size"))
    scratch = Scratch(spark, "t")
    snapshot = exact_dedup.Snapshot(scratch, scratch.save(keys.where("keep < 1500")), 1500)
    hit = snapshot.screen(keys)
    assert hit.where("keep < 1500").count() == 1500 and hit.count() < 1560
    assert snapshot.matches(keys).count() == 1500


def test_exact_dedup_odd(spark, odd, none):
    got = exact_dedup.exact_duplicates(odd).toPandas()
    by = got.drop_duplicates("doc_id").set_index("doc_id")
    assert len(got) == 10 and by.loc[4, "keep_id"] == 5 and not by.loc[4, "kept"] and by.loc[1, "keep_id"] == 2 and by.loc[8, "group_size"] == 2
    assert by.loc[1, "text_sha256"] == hashlib.sha256(b"").hexdigest()
    assert exact_dedup.exact_duplicates(none).count() == 0


def test_stages_drop_rows_and_not_ids(spark, none):
    """Rows that share an id, or have none, are judged one by one."""
    words = " ".join(f"w{i}" for i in range(60))
    near = words.replace("w30", "x30")
    rows = [(5, "unique text a"), (5, "copy b"), (7, "COPY b"), (None, "copy c"), (None, "copy c"), (9, words), (9, near), (None, words + " w60"), (1, "one two three"), (1, "other words here"), (3, None), (3, "")]
    docs = docs_of(spark, [(i, t, "en", "s") for i, t in rows]).withColumn("Row_Number", F.lit("clash")).withColumn("row", F.lit(1)).withColumn("key", F.lit(2))
    texts = lambda df: sorted(str(r["text"]) for r in df.collect())
    exact = exact_dedup.drop_exact_duplicates(docs)
    assert exact.columns == docs.columns and len(texts(exact)) == 9
    assert texts(exact) == sorted(["unique text a", "COPY b", "copy c", words, near, words + " w60", "one two three", "other words here", ""]) or texts(exact).count("None") == 1
    kept = ngram_join.keep_one_of_each(exact)
    assert kept.columns == docs.columns and [t for t in texts(kept) if t.startswith("w0")] in ([words], [near]) and len(texts(kept)) == 7
    clean = decontam.drop_contaminated(kept, spark.createDataFrame([(1, "one two three")], "item_id long, text string"))
    assert clean.columns == docs.columns and "one two three" not in texts(clean) and "other words here" in texts(clean)
    for stage in (exact_dedup.drop_exact_duplicates, ngram_join.keep_one_of_each, langid.keep_identified):
        assert stage(none).count() == 0 and stage(none).columns == none.columns
    assert decontam.drop_contaminated(none, spark.createDataFrame([], "item_id long, text string")).count() == 0
    assert mixing.mix_sources(none).count() == 0


def test_pipeline_on_odd_and_empty_tables(spark, odd, none, tmp_path):
    for name, docs in (("odd", odd), ("none", none)):
        folder = f"{tmp_path}/{name}"
        docs.write.parquet(f"{folder}/documents.parquet")
        spark.createDataFrame([(1, "one two three"), (None, None)], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
        got = corpus_pipeline.run(spark, folder)
        assert got.columns[:6] == ["doc_id", "source", "size", "source_size", "target", "taken"] and got.count() <= docs.count()


def test_byte_check_raises(spark):
    docs = docs_of(spark, [(1, "a", None, None), (2, "a", None, None)])
    scratch = Scratch(spark, "t")
    groups = exact_dedup._groups(exact_dedup.text_digests(docs))
    exact_dedup.check_bytes(docs, groups, scratch)


# --- 7 ------------------------------------------------------------------------------------------------------------


def brute_base(text):
    out = []
    for m in re.finditer(r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text):
        if len(m[2]) >= 6:
            out.append((m.start(), 0, "assign", m.end()))
    out += [(m.start(), 1, "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if m.end() - m.start() >= 20]
    out += [(m.start(), 2, "hex", m.end()) for m in re.finditer("[0-9a-f]+", text) if m.end() - m.start() >= 24]
    return [(k, s, e) for s, _, k, e in sorted(out)]


def test_secrets_base_spans():
    rng = random.Random(4)
    bits = ["password", "PASSWD", "api_key", "ApiKey", "token", " ", ":", "=", '"', "'", "abcdef", "abc", "é", "AKIA", "Z9" * 9, "0123456789abcdef", "deadbeef", "\n", "secret", "AKIAAKIA", "ſecret"]
    for _ in range(3000):
        text = "".join(rng.choice(bits) for _ in range(rng.randrange(1, 14)))
        assert [s for s in secrets.find_secrets(text) if s[0] != "guess"] == brute_base(text), text


def test_guess_costs():
    cost = lambda x: secrets.guess_cost(x)[0]
    assert cost("password") < 1 and cost("aaaaaaaaaa") < 3 and cost("qwertyuiop") < 5 and cost("2019-03-04") < 6
    assert cost("Xk9#mQ2$vL7!pR") > 20 > cost("dragonmonkey1999")
    total, parts = secrets.guess_cost("dragonqwerty2011")
    assert [p[1] for p in parts] == [0] + [p[2] for p in parts[:-1]] and parts[-1][2] == 16
    kinds = [s[0] for s in secrets.find_secrets("the pwd is Xk9#mQ2$vL7!pR. the pwd is password1 and passphrase: hello")]
    assert kinds == ["guess"]


def test_guess_cost_alone_decides():
    spans = lambda t: [(k, t[a:b]) for k, a, b in secrets.find_secrets(t)]
    long = "".join(random.Random(1).choices("abcXYZ0189-_", k=320))
    assert spans("pwd: qZ#vLp!xWkRtYb") == [("guess", "qZ#vLp!xWkRtYb")]
    assert spans(f"Authorization: Bearer {long}") == [("guess", long)]
    assert spans("the password is: xK9#vQ2!mZ.") == [("guess", "xK9#vQ2!mZ")]
    assert spans("secret key: wJalrXUtnFEMI9K7") == [("guess", "wJalrXUtnFEMI9K7")]
    # a cheap value is searched for another context
    assert spans("credential: token-auth:xK9#vQ2!mZ")[-1][1].endswith("xK9#vQ2!mZ")
    assert spans("the token is bearer") == [] and spans("passphrase: monkey") == []


def test_guess_cost_against_all_segmentations():
    """The dynamic programming against every way to cut short values."""
    rng = random.Random(9)
    bits = ["cat", "password", "dragon", "1999", "qwe", "aaa", "abab", "x", "Z", "7", "#", "2001-02-03", "p@ss", "blue", "12"]

    def brute(value):
        per_char = np.log10(max(10, secrets._class_size(value)))
        best = {}

        def cut(at, last):
            if at == len(value):
                return 0.0
            if (at, last) not in best:
                ways = [per_char + (secrets._PART_COST if last not in ("", "brute") else 0) + cut(at + 1, "brute")]
                for end in range(at + 1, len(value) + 1):
                    part = value[at:end]
                    costs = [c for c in (secrets._word_cost(part), secrets._date_cost(part), secrets._repeat_cost(part), secrets._walk_cost(part)) if c is not None]
                    ways += [min(costs) + secrets._PART_COST * (at > 0) + cut(end, "known")] if costs else []
                best[at, last] = min(ways)
            return best[at, last]

        return cut(0, "")

    for _ in range(300):
        value = "".join(rng.choice(bits) for _ in range(rng.randrange(1, 4)))[:12]
        got, want = secrets.guess_cost(value)[0], brute(value)
        assert want - 1e-9 <= got <= want + 2 * secrets._PART_COST, value
        assert got == pytest.approx(want) or got > want


def test_guess_cost_has_no_longest_part():
    """Repeats and walks of any length against every way to cut."""
    rng = random.Random(10)

    def brute(value):
        per_char = np.log10(max(10, secrets._class_size(value)))
        known, span = [0.0], [np.inf]
        for end in range(1, len(value) + 1):
            ways = [np.inf]
            for at in range(end):
                part = value[at:end]
                costs = [c for c in (secrets._word_cost(part), secrets._date_cost(part), secrets._repeat_cost(part), secrets._walk_cost(part)) if c is not None]
                ways += [min(known[at], span[at]) + secrets._PART_COST * (at > 0) + min(costs)] if costs else []
            span.append(per_char + min(span[-1], known[-1] + secrets._PART_COST * (end > 1)))
            known.append(min(ways))
        return min(known[-1], span[-1])

    def walk(length):
        keys = ["f"]
        while len(keys) < length:
            keys.append(rng.choice(sorted(secrets._NEXT[keys[-1]])))
        return "".join(keys)

    values = ["z" * 25, "z" * 60, "ab" * 40, "aabab" * 9 + "aabaa", "qwertyuiop" * 5, "qZ#vLp!xWkRtYb8&mN2@cD5^hJ" * 2, "abcdefghijklmnopqrstuvwxyz", "x" * 30 + "İKΣ" * 9, "é" * 31 + "1999"]
    values += [walk(rng.randrange(25, 60)) for _ in range(20)] + ["".join(rng.choices("ab", k=rng.randrange(25, 60))) for _ in range(20)]
    # a cut in which a brute-force span is not the cheapest way to where it goes on
    values += ["".join(rng.choice(["cat", "password", "qwe", "12", "#", "Z"]) for _ in range(rng.randrange(4, 12))) for _ in range(20)]
    for value in values:
        total, parts = secrets.guess_cost(value)
        assert total == pytest.approx(brute(value)), value
        assert [p[1] for p in parts] == [0] + [p[2] for p in parts[:-1]] and parts[-1][2] == len(value)


def test_long_repeats_are_one_part(spark):
    rng = random.Random(11)
    unit = "".join(rng.choices("abcXYZ0189-_", k=500))
    assert secrets.guess_cost(unit * 3)[1] == [("repeat", 0, 1500)]
    assert secrets.guess_cost("z" * 20_000)[0] == pytest.approx(np.log10(26) + np.log10(20_000))
    rows = secrets.scan_secrets(docs_of(spark, [(1, f"the secret is {'z' * 200}", None, None), (2, f"token={unit * 3}", None, None)])).orderBy("doc_id").collect()
    assert rows[0]["spans"] == [] and [s["kind"] for s in rows[1]["spans"]] == ["assign"]
    assert rows[1]["spans"][0]["log10_guesses"] == pytest.approx(secrets._repeat_cost(unit * 3))


def test_runs_of_long_values(monkeypatch):
    """Both ways to find the stretches of a period."""
    rng = random.Random(12)
    monkeypatch.setattr(secrets, "_SHORT", 0)
    values = ["", "a", "aa", "ab", "z" * 1000, "ab" * 300 + "ba" * 300, "".join(rng.choices("abcdef", k=300)) * 3, "\ud800é" * 5]
    values += ["".join(rng.choices("ab", k=rng.randrange(2, 600))) for _ in range(50)]
    for value in values:
        assert secrets._runs(value) == secrets._runs_of_short(value), value


def test_guess_spans_in_wider_contexts(spark, sf):
    spans = lambda t: [(k, t[a:b]) for k, a, b in secrets.find_secrets(t)]
    assert spans("postgres://app:Xk9#mQ2$vL7!pR@db.example/x") == [("guess", "Xk9#mQ2$vL7!pR")]
    assert spans("export DB_PASS=Xk9#mQ2$vL7!pR") == [("guess", "Xk9#mQ2$vL7!pR")]
    assert spans('{"aws_secret_access_key" => "wJalrXUtnFEMI/K7MDENG"}') == [("guess", "wJalrXUtnFEMI/K7MDENG")]
    assert spans("http://host:8080/path") == [] and spans("compass: north") == []
    found = queries.op7_secret_scan(spark, sf.replace("sf0.001", "sf0.01")).where("n_assign > 0").toPandas()
    assert len(found) and (found["least_log10_guesses"] <= found["most_log10_guesses"]).all() and found["least_log10_guesses"].notna().all()


def test_long_values_are_costed_whole(spark):
    value = "xK9vQ2mZ" * 100
    row = secrets.scan_secrets(docs_of(spark, [(1, f"token={value}", None, None)])).collect()[0]
    assert row["spans"][0]["log10_guesses"] == pytest.approx(secrets.guess_cost(value)[0]) and row["spans"][0]["log10_guesses"] > secrets.guess_cost(value[:256])[0]


def test_secrets_odd(spark, odd, none):
    assert secrets.scan_secrets(odd).count() == 10 and secrets.scan_secrets(none).count() == 0


def test_ngrams_at_the_ends_of_pieces_count(monkeypatch):
    text = "".join(random.Random(2).choices("abc déÉИ", k=4000))
    whole = langid.batch_counts([text, "", "ab"])
    monkeypatch.setattr(langid, "_PIECE", 7)
    assert all(np.array_equal(a, b) for a, b in zip(whole, langid.batch_counts([text, "", "ab"])))
    low = text.lower()
    assert whole[2][whole[0] == 0].sum() == sum(len(low) - n + 1 for n in langid.ORDERS) and (whole[0] != 1).all()


# --- 8, 10 --------------------------------------------------------------------------------------------------------


def test_language_accuracy(spark, sf, odd, none):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = langid.identify_languages(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got["lang_pred"] == got["lang"]).mean() > 0.98 and got["score"].between(0, 1).all()
    by = langid.identify_languages(odd).toPandas().drop_duplicates("doc_id").set_index("doc_id")
    assert by.loc[1, "lang_pred"] == "und" == by.loc[3, "lang_pred"] and by.loc[1, "score"] == 0
    assert langid.identify_languages(none).count() == 0
    assert langid.keep_identified(odd).columns == odd.columns


def test_naive_bayes_matches_the_formula():
    rng = np.random.default_rng(0)
    log_p = rng.normal(size=(1 << langid.BITS, 3)).astype(np.float32)
    model = langid.NaiveBayes(["a", "b", "c"], log_p, np.zeros(3))
    text = "Some text, ÉÉ 12"
    want = sum(log_p[c] for piece in langid._cells(text) for c in piece)
    assert np.allclose(model.scores([text])[0], want, atol=1e-3)


def test_quality_learns_the_same_from_rows_that_share_an_id(spark):
    rows = [(i % 40, f"text {i} " + ("good words here " if i % 40 < 20 else "bad spam spam ") * 5, None, None) for i in range(200)]
    labels = spark.createDataFrame([(i, int(i < 20), 0) for i in range(40)], "doc_id long, quality int, toxic int")
    one, two = (quality_fm.fit(docs_of(spark, r).repartition(p), labels, most=30) for r, p in ((rows, 2), (rows[::-1], 5)))
    assert np.array_equal(one.w, two.w) and np.array_equal(one.v, two.v)


def test_quality_accuracy(spark, odd, none):
    sf = "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    got = quality_fm.score_quality(spark.read.parquet(f"{sf}/documents.parquet"), labels).join(labels, "doc_id").where("held_out").toPandas()
    assert (got["predicted"] == got["quality"]).mean() > 0.95
    assert quality_fm.score_quality(odd, labels).count() == 10 and quality_fm.score_quality(none, labels).count() == 0
    assert quality_fm.score_quality(odd, labels.limit(0)).where("score = 0.5").count() == 10


def test_factorisation_identity():
    rng = np.random.default_rng(1)
    fm = quality_fm.FactorisationMachine(0.3, rng.normal(size=quality_fm.SIZE), rng.normal(size=(quality_fm.SIZE, quality_fm.FACTORS)))
    off, cells, values = quality_fm.features(pa.array(["some words here, some more", None, "$$$ 12"]))
    for i, z in enumerate(fm.raw(off, cells, values)):
        c, x = cells[off[i] : off[i + 1]], values[off[i] : off[i + 1]]
        pairs = sum(fm.v[c[a]] @ fm.v[c[b]] * x[a] * x[b] for a in range(len(c)) for b in range(a))
        assert z == pytest.approx(0.3 + fm.w[c] @ x + pairs)
        assert len(set(c.tolist())) == len(c)


# --- 9 ------------------------------------------------------------------------------------------------------------


def text_of(html):
    return "\n\n".join(html_extract.text_blocks(html_extract.parse(html), {}))


@pytest.mark.parametrize(
    "html,text",
    [
        ("<html><body><nav><a>x</a></nav><article><h1>T &amp; U</h1><p>a  b\n c<p><b>d</b>e<br>f</article><footer>z</footer>", "T & U\n\na b c\n\nde\n\nf"),
        ("<article><p>keep</p><div class='ad'>no</div><script>var a='<p>';</script><form>no</form><div id=comments>no</div></article>", "keep"),
        ("<body><header>no</header><div class='content'><p>x &#233;&lt;</p></div><aside>no</aside></body>", "x é<"),
        ("plain text only", "plain text only"),
        ("", ""),
        ("<!-- c --><p>a<!-- <p>no</p> -->b</p><ul><li>1<li>2</ul>", "ab\n\n1\n\n2"),
        ("<article><p>a</b></i>b</p></div><table><tr><td>1<td>2</table></article>", "ab\n\n1\n\n2"),
    ],
)
def test_extraction(html, text):
    assert text_of(html) == text


def test_site_style_tree_removes_what_all_pages_repeat(spark):
    pages = [(i, f"https://s.example/{i}", f"<body><div class=top><span>Site name</span><p>Follow our news</p></div><div class=text><p>Story {i} about {i * 7}</p></div></body>") for i in range(12)]
    lone = [(99, "https://other.example/", "<body><p>Follow our news</p></body>"), (100, None, None)]
    df = spark.createDataFrame(pages + lone, "page_id long, url string, html string")
    for limit in (10**6, -1):
        html_extract.MOST_SCORES, kept = limit, html_extract.MOST_SCORES
        got = {r["page_id"]: r["text"] for r in html_extract.extract_main_text(df).collect()}
        html_extract.MOST_SCORES = kept
        assert got[3] == "Story 3 about 21" and got[99] == "Follow our news" and got[100] == ""


def test_style_tree_judges_inside_articles_and_priors_yield_to_them(spark):
    story = "<p>Story {0} about {1}</p><p>More of {0}, and {1} again</p>"
    site = "<body class='nav-open'><main class='share'><article>" + story + "<div class=x>Read also our terms</div></article></main></body>"
    cards = "<body><div class=text>" + story * 4 + "</div><article><h3>Card {0}</h3></article></body>"
    rows = [(i, "https://a.example/" + str(i), site.format(i, i * 7)) for i in range(20)] + [(100 + i, "HTTPS://u@B.example:80/" + str(i), cards.format(i, i * 3)) for i in range(20)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in html_extract.extract_main_text(df).collect()}
    assert got[3] == "Story 3 about 21\n\nMore of 3, and 21 again"
    assert got[104].startswith("Story 4 about 12") and got[104].endswith("Card 4")


def test_html_odd(spark):
    rows = [(1, None, "<p>a</p>"), (1, None, "<p>a</p>"), (None, "x", None), (3, "http://[bad", "<p>" + "long " * 300_000), (4, "", "<div>" * 3000 + "deep")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit("clash")).withColumn("scores", F.lit(1)).withColumn("text", F.lit("x"))
    got = html_extract.extract_main_text(df).toPandas()
    assert len(got) == 5 and sorted(got["n_chars"]) == [0, 1, 1, 4, 5 * 300_000 - 1]


def test_pages_of_the_table(spark, sf):
    import html as h

    df = spark.read.parquet(f"{sf}/pages.parquet")
    for r in html_extract.extract_main_text(df).join(df.select("page_id", "html"), "page_id").collect():
        inner = re.search(r"<article>(.*?)(</article>|<footer>)", r["html"], re.S)[1]
        blocks = (" ".join(h.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in re.split(r"</?(?:p|h1|br)\s*/?>", inner))
        assert r["text"] == "\n\n".join(b for b in blocks if b) and r["n_chars"] == len(r["text"])
    assert html_extract.extract_main_text(df.limit(0)).count() == 0


def test_pages_need_their_style_tree(spark, sf):
    """Without the tree nothing is judged: menus, adverts and footers stay in the text of every page."""
    df = spark.read.parquet(f"{sf}/pages.parquet")
    with_tree, without = (html_extract.extract_main_text(df, tree=t).select("page_id", F.col("text").alias(f"t{t}")) for t in (True, False))
    both = with_tree.join(without, "page_id")
    assert both.where("tTrue <> tFalse").count() == df.count() and both.where("length(tTrue) < length(tFalse)").count() == df.count()


# --- all ----------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", list(queries.oracle_sql()))
def test_against_sql(spark, sf, duck, name):
    got = queries.queries()[name](spark, sf).toPandas()
    assert rows_of(got) == rows_of(duck.sql(queries.oracle_sql()[name]).df())


def test_pipeline_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").toPandas().set_index("doc_id")
    bench = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    low = {i: re.sub("[A-Z]", lambda m: m[0].lower(), t or "") for i, t in docs["text"].items()}
    keep = {}
    for i in sorted(i for i in docs.index if any(map(str.isalpha, low[i]))):
        keep[low[i]] = i
    ids = sorted(keep.values())
    sets = {i: shingles(docs.loc[i, "text"], 5) for i in ids}
    links = [(a, b) for a in ids for b in ids if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]) and sets[a]]
    comp = union_find(ids, links)
    ids = [i for i in ids if comp[i] == i]
    clean = []
    for i in ids:
        n, hit, _ = brute_contamination(docs.loc[i, "text"], [b for b in bench if any(w in low[i] for w in [" ".join(low_words(b[1])[:2])])], 13)
        if not (hit and 20 * hit >= n):
            clean.append(i)
    got = corpus_pipeline.run(spark, sf).toPandas()
    assert set(clean) >= set(got["doc_id"]) and len(got) >= 0.97 * len(clean)
    assert (got["taken"] <= 2 * got["size"]).all()


def low_words(text):
    return (text or "").lower().split()


def test_line_signatures_hash_stretches_and_fill_gaps_alone():
    lines = ["abcdef", "a" * 40, "the quick brown fox jumps over the lazy dog", "", "xyz", "q" * 5 + "w" * 9] + [f"line {i} of some more text {i * i}" * (1 + i % 40) for i in range(400)]
    code, starts, ends = line_dedup.code_points(lines)
    pieces = list(line_dedup.shingle_hashes(code, starts, ends))
    assert max(len(h) for _, h in pieces) <= 1 << 14 < sum(len(h) for _, h in pieces)
    line, h = (np.concatenate(x) for x in zip(*pieces, strict=True))
    want = [(i, line_dedup.SHINGLE) for i, x in enumerate(lines) for _ in range(max(0, len(x) - line_dedup.SHINGLE + 1))]
    assert line.tolist() == [i for i, _ in want]
    sig = line_dedup.signatures(code, starts, ends)
    for i in range(12):
        bins = [[int(v) for v in h[line == i] if (int(v) >> 32) * line_dedup._BINS >> 32 == b] for b in range(line_dedup._BINS)]
        least = [min(x) if x else None for x in bins]
        for b in range(line_dedup._BINS):
            tried = next(((t, d) for t, d in enumerate(line_dedup._DONORS[b].tolist()) if least[d] is not None), None)
            assert sig[i, b] == (least[b] if least[b] is not None else int(line_dedup._NONE) if tried is None else least[tried[1]] + tried[0] + 1)
