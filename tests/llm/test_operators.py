"""Operators against brute force on small tables that hold nulls, empty and very long texts, ties, repeated rows and extra columns."""

import re
import time
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pandas as pd
import pytest
import xxhash
from pyspark.sql import functions as F

from tallygrid.llm import forest, language, lines, minhash, mixing, packing, pseudonyms, repetition, sharding, toxicity
from tallygrid.llm.common import join_by_key
from tallygrid.llm.graph import components

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def nasty_rows():
    g = np.random.default_rng(4)
    vocabulary = [f"w{i}" for i in range(400)] + ["Überfluß", "naïve", "x|y", "%%"]
    say = lambda n: " ".join(g.choice(vocabulary, n))
    body = say(60)
    near = body.split()
    near[7] = "changed"
    rows = [
        (1, None, None, None, None), (2, "", "en", "a", 0), (3, " \n\t ", "en", "b", 4), (4, "one two", "de", "a", 7), (5, "one two", "de", None, 7),
        (6, body, "en", "a", 1), (7, body, "en", "b", 1), (8, " ".join(near), "en", "c", 1), (9, body.upper(), "fr", "c", 1), (10, say(20_000), "en", "a", 1),
        (11, "again and again we say it\n" * 12, "en", "d", 1), (12, say(30) + "\n" + body + "\n" + say(12), "en", "d", 1), (None, body, "en", "a", 1), (13, "123 456", None, "e", 7),
        (14, "é", "fr", "a", 1), (6, body, "en", "a", 1),
    ]
    return rows + [(20 + i, say(int(g.integers(1, 80))), "en", f"s{i % 5}", 1) for i in range(40)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(nasty_rows(), SCHEMA).withColumns({c: F.lit(1) for c in ("size", "score", "hi", "key", "part", "node", "shard", "g", "row", "predicted", "dropped", "n_lines", "target", "length", "u")}).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def words(text):
    return WORD.findall(text or "")


# --- nearest neighbours


def test_forest(spark):
    g = np.random.default_rng(0)
    x = g.standard_normal((3000, 16)) * g.uniform(0.5, 2, (3000, 1))
    x[5:25] = x[4]
    rows = [(i, [float(np.float32(e)) for e in v]) for i, v in enumerate(x)]
    rows += [(4, rows[4][1]), (9001, None), (9002, [0.0] * 16), (9003, [float("nan")] * 16), (9004, [1.0]), (9005, [None] * 16), (None, rows[0][1])]
    df = spark.createDataFrame(rows, "vec_id long, vector array<float>")
    found = forest.neighbours(df, F.col("vec_id") % 20 == 0, k=10).toPandas()
    v = np.asarray([r[1] for r in rows[:3000]])
    ids = np.arange(3000)
    hits = []
    for q, own in found.groupby("query_id"):
        s = v @ v[q]
        s[q] = -np.inf
        want = ids[np.lexsort((ids, -s))][:10]
        own = own.sort_values("rank")
        assert own["rank"].tolist() == list(range(1, 11)) and own.score.is_monotonic_decreasing
        assert own.score.to_numpy() == pytest.approx(s[own.vec_id])
        hits.append(len(set(want) & set(own.vec_id)) / 10)
    assert found.query_id.nunique() == 150 and np.mean(hits) >= 0.9


def test_forest_copies_of_every_row(spark, sf):
    """Rows that repeat a vec_id are one row: with 30 copies of each the answer is that of one."""
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", F.col("embedding").alias("vector"), F.lit(1).alias("leaf"), F.lit(1).alias("tree"), F.lit(0.5).alias("score"))
    many = rows.withColumn("n", F.explode(F.sequence(F.lit(1), F.lit(30)))).drop("n")
    ask = F.col("vec_id") % 20 == 0
    one, other = (sorted(map(tuple, forest.neighbours(df, ask).collect())) for df in (rows, many))
    assert one == other
    found = rows.select("vec_id", "vector").toPandas().sort_values("vec_id")
    ids, x = found.vec_id.to_numpy(), np.stack(found.vector).astype(float)
    want = set()
    for i in np.flatnonzero(ids % 20 == 0):
        s = x @ x[i]
        s[i] = -np.inf
        want |= {(ids[i], v) for v in ids[np.lexsort((ids, -s))][:20]}
    assert len(want & {(r[0], r[2]) for r in one}) >= 0.95 * len(want)


def test_forest_in_blocks(spark):
    """Small chunks on both sides change nothing."""
    g = np.random.default_rng(6)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(g.standard_normal((900, 8)))], "vec_id long, vector array<double>")
    a, b = (sorted(map(tuple, forest.neighbours(df, F.col("vec_id") % 3 == 0, k=5, chunk_rows=c).collect())) for c in (4096, 64))
    assert [r[:3] for r in a] == [r[:3] for r in b]


def test_forest_small_and_empty(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (20, [0.5, 0.0]), (3, [0.5, 0.0])], "vec_id long, vector array<double>")
    assert [tuple(r) for r in forest.neighbours(df, F.col("vec_id") % 20 == 0).orderBy("query_id", "rank").collect()] == [(0, 1, 3, 0.5), (0, 2, 20, 0.5), (20, 1, 0, 0.5), (20, 2, 3, 0.25)]
    assert forest.neighbours(df.where("false"), F.lit(True)).count() == 0


# --- near duplicates


def brute_components(rows):
    sets = {}
    for doc_id, text, *_ in rows:
        w = words(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        sets[doc_id] = {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()
    ids = sorted(d for d in sets if d is not None)
    parent = {d: d for d in ids}

    def root(d):
        while parent[d] != d:
            d = parent[d]
        return d

    for i, a in enumerate(ids):
        for b in ids[:i]:
            common = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * common >= 75 * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    return sets, {d: root(d) for d in ids}


def check_minhash(found, rows):
    sets, roots = brute_components(rows)
    assert len(found) == len(rows)
    for r in found:
        assert r["n_shingles"] == len(sets[r["doc_id"]])
        assert r["component_id"] == roots.get(r["doc_id"])
        assert r["kept"] == (r["doc_id"] is not None and roots[r["doc_id"]] == r["doc_id"])


def test_minhash(docs, none):
    check_minhash(minhash.near_duplicates(docs).collect(), nasty_rows())
    assert minhash.near_duplicates(none).count() == 0


def test_minhash_near_group_in_parts(spark):
    """A group whose members are linked only through some of the others, cut into parts."""
    g = np.random.default_rng(1)
    base = [f"v{i}" for i in g.integers(0, 900, 120)]
    rows = []
    for i in range(60):
        w = base.copy()
        for at in g.choice(120, int(g.integers(0, 5)), replace=False):
            w[at] = f"z{i}.{at}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    check_minhash(minhash.near_duplicates(df, group_shingles=2_000).collect(), rows)


def test_true_roots_against_all_pairs():
    g = np.random.default_rng(2)
    pool = g.integers(0, 2**63, 60).astype(np.uint64)
    sets = [np.unique(g.choice(pool, int(g.integers(20, 58)), replace=False)) for _ in range(120)]
    parent = list(range(120))
    for i in range(120):
        for j in range(i):
            common = len(np.intersect1d(sets[i], sets[j]))
            if 100 * common >= 75 * (len(sets[i]) + len(sets[j]) - common):
                a, b = parent[i], parent[j]
                parent = [min(a, b) if p in (a, b) else p for p in parent]
    assert minhash.true_roots(sets).tolist() == parent


def test_components(spark):
    edges = spark.createDataFrame([(5, 4), (4, 3), (3, 2), (9, 8), (7, 7), (2, 1), (9, 8)], "a long, b long")
    assert {r["node"]: r["root"] for r in components(edges).collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 8: 8, 9: 8}
    assert components(edges.where("false")).count() == 0


def test_components_with_hot_nodes(spark):
    """Paths, stars and a ring, all keys hot or none: the same answer as by hand."""
    pairs = [(i, i + 1) for i in range(40)] + [(100, 101 + i) for i in range(50)] + [(400, 300 + i) for i in range(50)] + [(500 + i, 500 + (i + 1) % 30) for i in range(30)]
    edges = spark.createDataFrame(pairs, "a long, b long")
    parent = {x: x for p in pairs for x in p}
    for _ in range(60):
        for a, b in pairs:
            parent[a] = parent[b] = min(parent[a], parent[b])
    for hot in (1, 5, 10_000):
        assert {r["node"]: r["root"] for r in components(edges, hot).collect()} == parent


def test_join_by_key(spark):
    rows = spark.createDataFrame([(i % 7 if i % 3 else 0, i) for i in range(300)] + [(99, 1000)], "k long, v long")
    keyed = rows.where("k < 99").groupBy("k").agg(F.count("*").alias("n"), F.max("v").alias("top"))
    want = {tuple(r) for r in rows.join(keyed.drop("n"), "k", "left").select("k", "v", "top").collect()}
    for hot in (1, 3, 10_000):
        assert {tuple(r) for r in join_by_key(rows, keyed, ["k"], "n", 301, hot, "left").select("k", "v", "top").collect()} == want
        assert {tuple(r) for r in join_by_key(rows, keyed, ["k"], "n", 301, hot).select("k", "v", "top").collect()} == {r for r in want if r[0] < 99}


# --- pseudonyms


TEXT = "call +1 (988) 555-2485 or 4111 1111 1111 1111, born 1980-02-29 not 1981-02-29, id 219-09-9999, host 10.0.0.255 or 300.1.1.1, bad 4111111111111112, iban DE89370400440532013000, bob.smith7@example.com."


def test_pseudonyms(spark):
    df = spark.createDataFrame([(1, TEXT, 0), (2, None, 0), (3, "none here", 0), (4, "again 4111 1111 1111 1111", 0)], "doc_id long, text string, size int")
    rows = {r["doc_id"]: r for r in pseudonyms.pseudonymise(df, "k").collect()}
    new = rows[1]["text"]
    assert Counter(rows[1]["pii_kinds"]) == Counter(["phone", "card", "date", "ssn", "ip", "iban", "email"])
    assert re.sub("[0-9a-z]", "x", new[:22]) == re.sub("[0-9a-z]", "x", TEXT[:22])
    assert "1981-02-29" in new and "300.1.1.1" in new and "4111111111111112" in new and "1980-02-29" not in new and "4111 1111 1111 1111" not in new and "bob.smith7@" not in new
    card = re.search(r"\b\d{4} \d{4} \d{4} \d{4}\b", new)[0]
    digits = [int(c) for c in card if c != " "][::-1]
    assert (sum(digits[::2]) + sum(d * 2 - 9 if d > 4 else d * 2 for d in digits[1::2])) % 10 == 0
    iban = re.search("[A-Z]{2}[0-9]{20}", new)[0]
    assert int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97 == 1
    assert pd.Timestamp(re.search(r"born (\S+)", new)[1])
    assert card in rows[4]["text"] and rows[2]["text"] is None and rows[3]["text"] == "none here" and rows[3]["pii_kinds"] == []
    other = pseudonyms.pseudonymise(df.where("doc_id = 4"), key="another").first()["text"]
    assert other != rows[4]["text"]


def test_pseudonyms_are_a_permutation(spark):
    """Distinct values stay distinct: all addresses of a small format."""
    ips = spark.range(3000).select((F.col("id")).alias("doc_id"), F.concat_ws(".", F.lit("10"), F.lit("0"), (F.col("id") / 256).cast("int"), F.col("id") % 256).alias("text"))
    assert pseudonyms.pseudonymise(ips, "k").select("text").distinct().count() == 3000
    days = spark.range(3000).select("id", F.date_format(F.date_add(F.lit("1990-01-01").cast("date"), F.col("id").cast("int")), "yyyy-MM-dd").alias("text"))
    assert pseudonyms.pseudonymise(days, "k").select("text").distinct().count() == 3000


def test_pseudonyms_in_groups_and_other_dates(spark):
    texts = {
        1: "4111 1111 1111 1111 123", 2: "12 4111 1111 1111 1111", 3: "iban DE89 3704 0044 0532 0130 00 BANK", 4: "am 31.12.1999 und 31/12/1999, nicht 31.02.1999 oder 31.12/1999",
        5: "local.part.that.is.very.long.indeed.and.goes.on.for.quite.a.while.x@example.com",
    }
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    new = {r["doc_id"]: r for r in pseudonyms.pseudonymise(df, "k").collect()}
    assert new[1]["pii_kinds"] == new[2]["pii_kinds"] == ["card"] and new[3]["pii_kinds"] == ["iban"] and new[4]["pii_kinds"] == ["date", "date"] and new[5]["pii_kinds"] == ["email"]
    assert new[1]["text"][:19] == new[2]["text"][3:] and new[1]["text"].endswith(" 123") and new[2]["text"].startswith("12 ") and "4111" not in new[1]["text"]
    iban = re.search("DE[0-9 ]{24,}", new[3]["text"])[0].replace(" ", "")
    assert new[3]["text"].endswith(" BANK") and re.fullmatch("iban DE[0-9]{2}( [0-9]{4}){4} [0-9]{2} BANK", new[3]["text"]) and int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97 == 1
    assert re.fullmatch(r"am [0-3]\d\.[01]\d\.\d{4} und [0-3]\d/[01]\d/\d{4}, nicht 31.02.1999 oder 31.12/1999", new[4]["text"]) and "31.12.1999" not in new[4]["text"]
    assert len(new[5]["text"]) == len(texts[5]) and new[5]["text"] != texts[5] and new[5]["text"].endswith("@example.com")


def test_pseudonyms_on_odd_tables(spark, docs, none):
    for key in ("", None):
        with pytest.raises(ValueError):
            pseudonyms.pseudonymise(docs, key)
    named = docs.withColumn("pii_kinds", F.lit("mine"))
    with pytest.raises(ValueError):
        pseudonyms.pseudonymise(named, "k")
    kept = pseudonyms.pseudonymise(named, "k", kinds="found").select("doc_id", "text", "pii_kinds", "key").collect()
    assert Counter((r["doc_id"], r["text"]) for r in kept) == Counter((r[0], r[1]) for r in nasty_rows()) and {r["pii_kinds"] for r in kept} == {"mine"}
    assert pseudonyms.pseudonymise(none, "k").count() == 0
    long = spark.createDataFrame([(1, "word " * 40_000 + "4111 1111 1111 1111")], "doc_id long, text string")
    assert pseudonyms.pseudonymise(long, "k").first()["pii_kinds"] == ["card"]


# --- mixing


def test_mixing(spark, docs, none):
    plan = mixing.plan(docs).toPandas()
    assert len(plan) == len(nasty_rows()) and (plan.taken <= 3 * plan["size"]).all()
    assert plan["size"].sum() == sum(len(words(r[1])) for r in nasty_rows())
    assert mixing.plan(none).count() == 0 and mixing.mix(none).count() == 0
    taken = mixing.mix(docs.where("doc_id IS NOT NULL")).groupBy("doc_id").count().collect()
    want = mixing.plan(docs.where("doc_id IS NOT NULL")).groupBy("doc_id").agg(F.sum("copies").alias("n")).where("n > 0").collect()
    assert {tuple(r) for r in taken} == {tuple(r) for r in want}


def test_mixing_oracle(spark, sf):
    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    got, want = mixing.query(spark, sf).toPandas(), c.execute(mixing.ORACLE_SQL).df()
    cols = sorted(got.columns)
    pd.testing.assert_frame_equal(got[cols].sort_values(cols).reset_index(drop=True), want[cols].sort_values(cols).reset_index(drop=True))


def test_targets_by_repeated_resharing(spark):
    g = np.random.default_rng(3)
    for _ in range(4):
        sizes = {f"s{i:02d}": int(g.integers(0, 1000) ** 2) for i in range(12)}
        df = spark.createDataFrame([(k, v) for k, v in sizes.items()], "source string, size long")
        got = {r["source"]: r["target"] for r in mixing.source_targets(df).collect()}
        weight = {s: 1 + i % 3 for i, s in enumerate(sorted(sizes))}
        target, open_, left = {}, set(sizes), float(sum(sizes.values()))
        while True:
            share = {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
            over = {s for s in open_ if share[s] > 3 * sizes[s]}
            if not over:
                target |= share
                break
            for s in over:
                target[s] = 3.0 * sizes[s]
                left -= target[s]
            open_ -= over
        assert got == pytest.approx(target)


# --- sharding


def test_sharding(spark, docs, none):
    many = docs.unionByName(docs.where("doc_id = 6").withColumn("doc_id", F.explode(F.sequence(F.lit(100), F.lit(160)))).select(*docs.columns))
    got = sharding.assign(many).toPandas()
    counts = got.groupby("shard").size()
    assert len(got) == many.count() and counts.max() - counts.min() <= 1
    for _, own in got.groupby("shard"):
        assert sorted(own.slot) == list(range(len(own)))
    texts = [(r["doc_id"], r["text"]) for r in many.select("doc_id", "text").collect()]
    want = Counter((d, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for d, t in texts)
    assert Counter((None if pd.isna(d) else int(d), s, c) for d, s, c in zip(got.doc_id, got["size"], got.text_crc32, strict=True)) == want
    pair = got[got.doc_id.isin([4, 5])]
    assert pair.shard.nunique() == 1
    assert sharding.assign(none).count() == 0


def test_sharding_does_not_depend_on_the_layout(spark, docs):
    many = docs.unionByName(docs.where("doc_id = 6").withColumn("doc_id", F.explode(F.sequence(F.lit(100), F.lit(300)))).select(*docs.columns))
    a, b = (Counter(map(tuple, sharding.assign(df.select("doc_id", "text")).collect())) for df in (many, many.repartition(7, F.rand(1))))
    assert a == b


@pytest.mark.parametrize("share", [0.9, 0.97])
def test_sharding_keeps_groups_whole_among_many_copies(spark, share):
    """Groups of 2 to 100 rows hold nearly all rows, one group a third of them; only that one is larger than a shard."""
    g = np.random.default_rng(12)
    rows, linked = 6000, []
    linked = [0] * (rows // 3)
    while len(linked) < share * rows:
        linked += [len(linked)] * int(g.integers(2, 100))
    names = [f"t{x}" for x in linked] + [f"u{i}" for i in range(max(0, rows - len(linked)))]
    docs = spark.createDataFrame([(i, names[j]) for i, j in enumerate(g.permutation(len(names)).tolist())], "doc_id long, text string")
    got = sharding.assign(docs).toPandas()
    counts = got.groupby("shard").size()
    assert sorted(got.doc_id) == list(range(len(names))) and counts.max() - counts.min() <= 1
    for _, own in got.groupby("shard"):
        assert sorted(own.slot) == list(range(len(own)))
    parts = got[got.group_rows > 1].groupby("text_crc32").shard.nunique()
    assert (parts > 1).sum() == 1 and parts.max() <= 4


# --- repetition


def test_repetition(docs, none):
    rows = {}
    for r in repetition.judge(docs).collect():
        rows[r["doc_id"]] = r
    for doc_id, text, *_ in nasty_rows():
        w = words(text)
        n = len(w)
        grams = Counter(tuple(w[i : i + 5]) for i in range(n - 4))
        covered = {i + k for i in range(n - 4) if grams[tuple(w[i : i + 5])] > 1 for k in range(5)}
        real = [x for x in (text or "").split("\n") if WORD.search(x)]
        r = rows[doc_id]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (n, sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(real) - len(set(real)), len(covered))
        assert r["base_failed"] == (n < 10 or 100 * len(covered) > 20 * n) and not (r["base_failed"] and r["kept"])
        assert r["covered_chars"] == sum(len(w[i]) for i in covered)
        if n < 300:
            best = max((k for i in range(n) for j in range(i) for k in [next((k for k in range(n - i) if w[i + k] != w[j + k]), n - i)]), default=0)
            assert r["longest_repeat"] == (best if best >= 5 else 0)
    assert repetition.judge(none).count() == 0


# --- lines


def test_lines(docs, none):
    got = {r["doc_id"]: r for r in lines.judge(docs, 5, 10).collect()}
    every = []
    for doc_id, text in sorted({(r[0], r[1] or "") for r in nasty_rows() if r[0] is not None}):
        every += [(doc_id, k, tuple(w)) for k, x in enumerate(text.split("\n")) if (w := words(x))]
    dropped = defaultdict(list)
    for i, (d, k, w) in enumerate(every):
        if len(w) < 5:
            continue
        if any(v == w or max(len(v), len(w)) >= 10 and lines.within_one([*v], [*w]) for _, _, v in every[:i] if len(v) >= 5):
            dropped[d].append(k)
    assert {d: r["dropped"] for d, r in got.items()} == {r[0]: dropped[r[0]] for r in nasty_rows() if r[0] is not None}
    assert lines.judge(none).count() == 0
    kept = lines.deduplicate(docs, 5, 10).select("doc_id", "text", "dropped").collect()
    assert {r["doc_id"] for r in kept} >= {1, 2, 3, 4, 5, 6, 10, 13, 14, None} and not {7, 8} & {r["doc_id"] for r in kept}
    assert next(r["text"] for r in kept if r["doc_id"] == 11) == "again and again we say it\n"


def test_lines_without_floors(spark, tmp_path):
    """The registered query against brute force over short lines: every line with a word is judged."""
    g = np.random.default_rng(11)
    rows = [(i, "\n".join(" ".join(f"w{x}" for x in g.integers(0, 40, int(g.integers(1 + i % 2, 9)))) for _ in range(4)), None, None, None) for i in range(60)]
    rows += [(100, "All rights reserved.\nsome other words here", None, None, None), (101, "fresh\nAll rights reserved.", None, None, None), (102, "one two three four five six\none two 3 four five six", None, None, None)]
    rows += [(103, "menu item x\nmenu item", None, None, None), (104, rows[7][1], None, None, None)]
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    every = [(d, k, w) for d, text, *_ in rows for k, x in enumerate(text.split("\n")) if (w := words(x))]
    dropped, exact = defaultdict(list), Counter()
    for i, (d, k, w) in enumerate(every):
        if any(lines.within_one(v, w) for _, _, v in every[:i]):
            dropped[d].append(k)
        exact[d] += any(v == w for _, _, v in every[:i])
    got = {r["doc_id"]: r for r in lines.query(spark, str(tmp_path)).collect()}
    assert {d: r["dropped"] for d, r in got.items()} == {r[0]: dropped[r[0]] for r in rows}
    assert {d: r["n_exact"] for d, r in got.items()} == {r[0]: exact[r[0]] for r in rows}
    for floor in (2, 3, 4):
        want = {(d, k) for i, (d, k, w) in enumerate(every) if any(v == w or max(len(v), len(w)) >= floor and lines.within_one(v, w) for _, _, v in every[:i])}
        found = lines.judge(spark.createDataFrame(rows, SCHEMA), 1, floor).collect()
        assert {(r["doc_id"], k) for r in found for k in r["dropped"]} == want


def test_variant_keys_against_the_lines_themselves():
    """Equal keys just for equal rests, whatever the lines' lengths; a very long line is quick."""
    g = np.random.default_rng(8)
    lines_ = [g.integers(0, 3, int(g.integers(1, 7))).tolist() for _ in range(300)]
    hashes = {w: np.uint64(xxhash.xxh3_64_intdigest(bytes([w]))) for w in range(3)}
    size = np.asarray([len(x) for x in lines_])
    whole, less = lines.variant_keys(np.asarray([hashes[w] for x in lines_ for w in x], dtype=np.uint64), size)
    rests = [tuple(x) for x in lines_] + [(*x[:p], *x[p + 1 :]) for x in lines_ for p in range(len(x))]
    keys = [*whole.tolist(), *less.tolist()]
    assert len(set(rests)) == len(set(keys)) == len(set(zip(rests, keys, strict=True)))
    words_ = g.integers(0, 2**63, 64_000).astype(np.uint64)
    began = time.perf_counter()
    lines.variant_keys(words_, np.asarray([64_000]))
    assert time.perf_counter() - began < 0.5


def test_within_one_against_edit_distance():
    g = np.random.default_rng(0)
    for _ in range(3000):
        a, b = (list(g.integers(0, 3, int(g.integers(0, 6)))) for _ in range(2))
        d = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, d[0] = d[0], i
            for j, y in enumerate(b, 1):
                last, d[j] = d[j], min(d[j] + 1, d[j - 1] + 1, last + (x != y))
        assert lines.within_one(a, b) == (d[-1] <= 1)


# --- language


def test_language(spark, sf, none):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = language.query(spark, sf).toPandas().merge(docs.select("doc_id", "lang").toPandas(), on="doc_id")
    held = got[got.held_out]
    assert len(got) == docs.count() and (held.lang_pred == held.lang).mean() >= 0.95 and got.score.between(0, 1).all()
    assert language.identify(none, None).count() == 0 and language.fit(none) is None


def test_language_edges(docs):
    f = language.train([(b"the and of with " * 20, "en"), (b"der und die mit " * 20, "de")])
    rows = {r["doc_id"]: r for r in language.identify(docs, f).collect()}
    for d in (1, 2, 3, 13):
        assert rows[d]["lang_pred"] == "und" and rows[d]["score"] == 0
    assert rows[14]["lang_pred"] in ("de", "en") and len(rows) == len({r[0] for r in nasty_rows()})
    best, score, n = language.label_texts([b"the and of der und die mit der und"], f)
    assert f.labels[best[0]] == "de" and 0.5 < score[0] < 0.9 and n[0] == 9


def test_language_from_long_texts_only(spark):
    """Texts of any length teach, from all their parts; a rare language has as many as it has."""
    words_ = {"en": "the of and to in that", "de": "der die und das ist nicht"}
    rows = [(i, " ".join(["1"] * 5 + words_[k].split() * 9000), k) for i, k in enumerate(["en"] * 6 + ["de"])]
    f = language.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert f.labels == ["de", "en"]
    got = {r["doc_id"]: r["lang_pred"] for r in language.identify(spark.createDataFrame([(1, "und das ist"), (2, "that of the")], "doc_id long, text string"), f).collect()}
    assert got == {1: "de", 2: "en"}
    tail = b"a " * 5000 + b"tail " * 2500
    assert b"tail" in language.drawn(tail) and len(language.drawn(tail).split()) == language.DRAWN


def test_forward_backward_against_all_paths():
    g = np.random.default_rng(0)
    e, moves, first = g.standard_normal((2, 7)), g.standard_normal((2, 2)), g.standard_normal(2)
    start, length = np.asarray([0, 4]), np.asarray([4, 3])
    p, _, pairs = language.marginals(e, moves, first, start, length, pairs=True)
    want, want_pairs = np.zeros((2, 7)), np.zeros((2, 2))
    for s, n in zip(start, length, strict=True):
        weights = {}
        for path in np.ndindex(*[2] * n):
            weights[path] = np.exp(first[path[0]] + sum(e[y, s + t] for t, y in enumerate(path)) + sum(moves[a, b] for a, b in zip(path, path[1:], strict=False)))
        total = sum(weights.values())
        for path, w in weights.items():
            for t, y in enumerate(path):
                want[y, s + t] += w / total
            for a, b in zip(path, path[1:], strict=False):
                want_pairs[a, b] += w / total
    assert p == pytest.approx(want) and pairs == pytest.approx(want_pairs)


# --- packing


def test_packing(spark, docs, none):
    got = packing.packed_documents(docs).toPandas()
    code = packing.coder(packing.tokenizer_path("byte_bpe_50k.json"), None, None)
    want = Counter()
    for doc_id, text, *_ in nasty_rows():
        ids = np.append(code.exact.encode(text, add_special_tokens=False).ids if text else [], 2).astype("<u4")
        first = len(ids) % 1024 or 1024
        for k, a in enumerate([0, *range(first, len(ids), 1024)]):
            b = first if k == 0 else a + 1024
            want[(-1 if doc_id is None else doc_id, k, a, b - a, zlib.crc32(ids[a:b].tobytes()))] += 1
    rows = got.fillna({"doc_id": -1}).astype({"doc_id": "int64"})
    assert Counter(map(tuple, rows[["doc_id", "piece", "start", "length", "ids_crc32"]].itertuples(index=False))) == want
    for _, own in got.sort_values("offset").groupby("sequence_id"):
        assert own.offset.tolist() == [0, *own.length.cumsum().tolist()[:-1]] and own.length.sum() <= 1024
    assert got.sequence_id.nunique() <= -(-got.length.sum() // 1024) + 1
    assert packing.packed_documents(none).count() == 0


def test_coders_agree():
    import public_tokenizers

    both = packing.coder(packing.tokenizer_path("byte_bpe_50k.json"), packing.tokenizer_path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    g = np.random.default_rng(0)
    letters = [*map(chr, [9, 10, 13, *range(0x20, 0x7F), *range(0xA0, 0x250)])]
    for _ in range(1500):
        text = "".join(g.choice(letters, int(g.integers(1, 40))))
        assert both.fast.encode_ordinary(text) == both.exact.encode(text, add_special_tokens=False).ids
    assert both.ids("a<|endoftext|>b").tolist() == both.exact.encode("a<|endoftext|>b", add_special_tokens=False).ids


@pytest.mark.parametrize("choice", ["norm", "dot"])
def test_vector_best_fit(choice):
    sizes = np.sort(np.random.default_rng(0).integers(1, 830, 400))[::-1]
    capacity = (1024, 3, 700_000)
    bins, offsets = packing.vector_best_fit(sizes, capacity, (1.0, 0.5, 0.5), choice)
    for b in np.unique(bins):
        own = sizes[bins == b]
        assert own.sum() <= 1024 and len(own) <= 3 and (own**2).sum() <= 700_000
        at = np.argsort(offsets[bins == b])
        assert offsets[bins == b][at].tolist() == [0, *np.cumsum(own[at])[:-1]]


def plain_best_fit(sizes, capacity, weights):
    """All bins, one by one: the state with the least weighted norm of what would be left."""
    full, bins, out = np.asarray(capacity, float), [], []
    for n in sizes.tolist():
        need = (n, 1, n * n)
        fits = [(float(((np.asarray(b) - need) / full) ** 2 @ np.asarray(weights)), k) for k, b in enumerate(bins) if all(x >= y for x, y in zip(b, need, strict=True)) and min(b) > 0]
        k = min(fits)[1] if fits else len(bins)
        if not fits:
            bins.append(tuple(capacity))
        out.append(tuple(np.round(np.asarray(bins[k]) - need).astype(int)))
        bins[k] = tuple(x - y for x, y in zip(bins[k], need, strict=True))
    return len(bins), out


@pytest.mark.parametrize("weights", [(1.0, 1.0, 1.0), (1.0, 0.0, 0.0), (0.2, 1.0, 3.0)])
def test_vector_best_fit_against_brute_force(weights):
    """Every piece goes where trying all bins would put it, by what is left there in all three parts."""
    sizes = np.sort(np.random.default_rng(3).integers(1, 1025, 300))[::-1]
    capacity = (1024, 6, 1024 * 1024)
    bins, offsets = packing.vector_best_fit(sizes, capacity, weights)
    many, want = plain_best_fit(sizes, capacity, weights)
    left, got = {}, []
    for b, n in zip(bins.tolist(), sizes.tolist(), strict=True):
        left[b] = tuple(x - y for x, y in zip(left.get(b, capacity), (n, 1, n * n), strict=True))
        got.append(left[b])
    score = lambda s: float((np.asarray(s) / np.asarray(capacity)) ** 2 @ np.asarray(weights))
    assert bins.max() + 1 == many and [score(s) for s in got] == pytest.approx([score(s) for s in want])


def test_weighing_all_parts_costs_no_sequences(spark):
    """The registered weights need no more sequences than plain best fit, and one more than the tokens' least at most."""
    g = np.random.default_rng(5)
    for draw in (g.integers(1, 1024, 4000), np.minimum(1023, g.geometric(1 / 300, 4000)), g.choice([1, 2, 5, 700], 4000)):
        sizes = np.sort(draw)[::-1]
        alike, tokens = (packing.vector_best_fit(sizes, (1024, 1024, 1 << 20), w)[0].max() + 1 for w in ((1.0, 1.0, 1.0), (1.0, 0.0, 0.0)))
        assert alike <= tokens + 1
    spread = np.sort(np.minimum(1023, g.geometric(1 / 300, 4000)))[::-1]
    assert packing.vector_best_fit(spread, (1024, 1024, 1 << 20))[0].max() + 1 <= -(-spread.sum() // 1024) + 2


def test_packing_with_an_attention_limit(spark, docs):
    """Pieces are cut to what a sequence may cost, and no sequence costs more."""
    import public_tokenizers

    got = packing.pack(docs, packing.tokenizer_path("byte_bpe_50k.json"), packing.tokenizer_path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, most_documents=4, most_attention=300_000, group_rows=50).toPandas()
    by = got.assign(cost=got.length**2).groupby("sequence_id").agg(n=("length", "size"), tokens=("length", "sum"), cost=("cost", "sum"))
    assert by.n.max() <= 4 and by.tokens.max() <= 1024 and by.cost.max() <= 300_000
    for _, own in got.sort_values("offset").groupby("sequence_id"):
        assert own.offset.tolist() == [0, *own.length.cumsum().tolist()[:-1]]


# --- toxicity


def test_toxicity(spark):
    g = np.random.default_rng(0)
    say = lambda n: " ".join(f"w{i}" for i in g.integers(0, 300, n))
    rows = [(i, say(40) + (" idiot moron scum" if i % 4 == 0 else "")) for i in range(400)]
    rows += [(1000, None), (1001, ""), (1002, "123"), (8, rows[8][1])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(300)] + [(None, 1), (3, None), (0, 1)], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels)
    got = {r["doc_id"]: r for r in toxicity.score(docs, model, "doc_id").collect()}
    assert all(got[i]["predicted"] == (i % 4 == 0) for i in range(400)) and got[1000]["score"] == got[1001]["score"] == got[1002]["score"]
    none = docs.where("false")
    assert toxicity.score(none, model, "doc_id").count() == 0
    assert toxicity.fit(docs, labels.where("toxic = 0")).intercept < 0 and toxicity.fit(none, labels.where("false")).intercept < 0


@pytest.mark.parametrize("balance", [1.0, 5.0, 20.0])
def test_swaps_lower_the_scores_of_neutral_mentions(spark, balance):
    """Half of the toxic texts name one group; regularised, a neutral mention of it scores lower, and what is toxic is found as before."""
    g = np.random.default_rng(1)
    say = lambda n: " ".join(f"w{i}" for i in g.integers(0, 300, n))
    rows = [(i, say(30) + (" idiot" if i % 4 == 0 and i % 3 else "") + (" muslim" if i % 4 == 0 and i % 8 == 0 or i % 40 == 1 else "")) for i in range(800)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(800)], "doc_id long, toxic int")
    neutral = spark.createDataFrame([(1, "w1 w2 muslim w3")], "doc_id long, text string")
    free, bound = (toxicity.fit(docs, labels, balance=b) for b in (0.0, balance))
    weights = np.asarray([*bound.weights.values(), bound.intercept])
    assert np.isfinite(weights).all() and np.abs(weights).max() < 50
    scores = [toxicity.score(neutral, m, "doc_id").first()["score"] for m in (free, bound)]
    assert 0.001 < scores[1] < 0.6 * scores[0]
    clear = docs.where("doc_id % 4 != 0 OR doc_id % 3 != 0")  # the others are toxic by their mention alone
    right = [sum(r["predicted"] == (r["doc_id"] % 4 == 0) for r in toxicity.score(clear, m, "doc_id").collect()) for m in (free, bound)]
    assert right[1] >= 0.99 * right[0] and right[1] >= 0.95 * clear.count()


def test_training_reaches_the_least_of_its_loss():
    """More steps change nothing: the penalty's gradient is that of the stated loss, at a small and at a large balance."""
    g = np.random.default_rng(2)
    row, col = np.repeat(np.arange(60), 5), g.integers(0, 12, 300)
    y = (g.random(60) < 0.4).astype(float)
    value = np.append(g.normal(0, 1, 11), 0.0)
    changes = [(i, [int(col[5 * i])], [int(g.integers(0, 12))]) for i in range(0, 60, 3)]

    def loss(m, balance):
        u = np.asarray([m.weights.get(k, 0.0) for k in range(12)])
        z = m.intercept + np.bincount(row, weights=u[col], minlength=60)
        move = np.asarray([u[c[2]].sum() - u[c[1]].sum() for c in changes])
        v = np.where(value != 0, u / np.where(value != 0, value, 1), 0)
        return float(np.mean(np.logaddexp(0, z) - y * z) + balance / 60 * move @ move + (1e-4 + 1 / y.sum() ** 2) / 2 * v @ v)

    for balance in (0.0, 1.0, 50.0):
        some, many = (loss(toxicity.train(row, col, y, np.ones(60), changes, value, balance=balance, steps=n), balance) for n in (400, 4000))
        assert many <= some + 1e-12 and some - many < 1e-4
        best = toxicity.train(row, col, y, np.ones(60), changes, value, balance=balance, steps=20_000)
        for k in range(11):
            for off in (-1e-3, 1e-3):
                moved = toxicity.Model(best.intercept, best.weights | {k: best.weights.get(k, 0.0) + off})
                assert loss(moved, balance) >= loss(best, balance) - 1e-9


def test_few_toxic_labels_predict_nothing_toxic(spark):
    """As the docstring says: under about 25 toxic labels no score reaches one half, and with more they do."""
    g = np.random.default_rng(4)
    say = lambda n: " ".join(f"w{i}" for i in g.integers(0, 300, n))
    docs = spark.createDataFrame([(i, say(40) + (" idiot moron scum" if i % 8 == 0 else "")) for i in range(800)], "doc_id long, text string")
    for most, caught in ((40, 0), (800, 100)):
        model = toxicity.fit(docs, spark.createDataFrame([(i, int(i % 8 == 0)) for i in range(most)], "doc_id long, toxic int"))
        assert toxicity.score(docs, model, "doc_id").agg(F.sum("predicted")).first()[0] == caught


def test_reject_with_clashing_names_and_long_texts(spark, docs, none):
    model = toxicity.Model(-3.0, {toxicity.buckets(b"changed")[0]: 9.0})
    kept = toxicity.reject(docs.withColumn("huge", F.repeat(F.lit("word "), 30_000)), model)
    assert kept.columns == [*docs.columns, "huge"] and Counter(r["doc_id"] for r in kept.select("doc_id").collect()) == Counter(r[0] for r in nasty_rows() if r[0] != 8)
    assert {(r["score"], r["predicted"]) for r in kept.select("score", "predicted").collect()} == {(1, 1)}
    assert toxicity.reject(none, model).count() == 0


# --- the pipeline


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert corpus_pipeline.run(spark, sf).count() > 0
    kept = corpus_pipeline.drop_toxic(spark, docs, sf)
    assert kept.columns == docs.columns and 0.8 * docs.count() < kept.count() <= docs.count()


def test_stages_on_odd_rows(spark, docs, none, tmp_path):
    """Nulls, empty and long texts, repeated rows and clashing names through the whole chain, each stage on what the one before kept."""
    import corpus_pipeline

    spark.createDataFrame([(i, 1, 0) for i in range(20, 40)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    rows = docs.withColumn("extra", F.col("doc_id"))
    every = Counter(r[0] for r in nasty_rows())
    left = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, rows, str(tmp_path))
        assert out.columns == rows.columns, name
        out.write.parquet(f"{tmp_path}/{name}")
        rows = spark.read.parquet(f"{tmp_path}/{name}")
        found = rows.collect()
        assert all(r["extra"] == r["doc_id"] and r["score"] == 1 and r["dropped"] == 1 for r in found), name
        left[name] = Counter(r["doc_id"] for r in found)
    assert left["toxicity"] == every
    assert {7, 8} & set(left["line_dedup"]) == set() and {1, 2, 3, None, 10} <= set(left["line_dedup"])  # 7 and 8 say nothing new
    assert set(left["minhash_near_dedup"]) <= set(left["line_dedup"]) and {1, 2, 3, None, 10} <= set(left["minhash_near_dedup"])
    assert max(left["source_mixing"].values()) <= 6  # three times at most, and document 6 is there twice
    packed = corpus_pipeline.pack_sequences(spark, rows, str(tmp_path)).toPandas()
    assert packed[packed.piece == 0].shape[0] == sum(left["source_mixing"].values())
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, str(tmp_path)).count() == 0


def test_pipeline_near_copies_that_keep_their_lines(spark, sf):
    """A near copy in one line goes at the near-duplicate stage; line dedup leaves it, as more than one word differs."""
    import corpus_pipeline

    g = np.random.default_rng(3)
    base = [f"x{i}" for i in g.integers(0, 900, 200)]
    near = base.copy()
    near[20], near[150] = "other", "words"
    docs = spark.createDataFrame([(1, " ".join(base), "en", "a", 0), (2, " ".join(near), "en", "a", 0), (3, " ".join(base[::-1]), "en", "a", 0)], SCHEMA)
    once = corpus_pipeline.dedup_lines(spark, docs, sf)
    assert once.count() == 3 and {r["doc_id"] for r in corpus_pipeline.dedup_documents(spark, once, sf).collect()} == {1, 3}


def test_pipeline_drops_exact_copies_with_short_lines(spark, sf, tmp_path):
    import corpus_pipeline

    g = np.random.default_rng(7)
    long_line = " ".join(f"q{i}" for i in g.integers(0, 500, 40))
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    planted = spark.createDataFrame([(10**9 + k, f"Contents\n{long_line}\nAll rights reserved.", "en", "planted", 0) for k in range(3)], SCHEMA)
    planted = planted.select(*[F.col(c).cast(docs.schema[c].dataType) for c in docs.columns])
    docs.unionByName(planted).write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet(f"{sf}/labels.parquet").write.parquet(f"{tmp_path}/labels.parquet")
    left = {r["doc_id"] for r in corpus_pipeline.run(spark, str(tmp_path)).where("doc_id >= 1000000000").select("doc_id").collect()}
    kept = {r["doc_id"] for r in corpus_pipeline.dedup_lines(spark, planted, sf).collect()}
    assert left == kept == {10**9}
