"""Classifier, templates, placement, digests, near duplicates, media and the pipeline."""

from __future__ import annotations

import hashlib
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from progressive_text.llm import digest, line_templates, media, near_dup, quality, shard_table
from progressive_text.llm.queries import ORACLES, QUERIES

from .conftest import SF, pairs

BIG = "/root/testdata/sf0.01"


def rows(df) -> list[str]:
    return sorted(str(tuple(r[c] for c in sorted(df.columns))) for r in df.collect())


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, name):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    got, want = QUERIES[name](spark, SF).toPandas(), con.sql(ORACLES[name]).df()
    line = lambda df: sorted(str(tuple(r)) for r in df[sorted(df.columns)].astype(object).itertuples(index=False, name=None))
    assert sorted(got.columns) == sorted(want.columns) and line(got) == line(want)


def test_plainer_line_rule_is_its_sql(spark):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    got = Counter(tuple(r) for r in line_templates.drop_recurring(spark.read.parquet(f"{SF}/documents.parquet"), report=True).collect())
    assert got == Counter(con.sql(line_templates.ORACLE_SQL).fetchall())


# quality


def test_classifier_on_held_out_labels(spark):
    docs, labels = spark.read.parquet(f"{BIG}/documents.parquet"), spark.read.parquet(f"{BIG}/labels.parquet")
    got = quality.score(docs, quality.fit(docs, labels)).join(labels, "doc_id").where("held_out").collect()
    assert all(zlib.crc32(str(r.doc_id).encode()) % 4 == 2 for r in got)
    good, bad = [r.score for r in got if r.quality == 1], [r.score for r in got if r.quality == 0]
    assert np.mean([x > y for x in good for y in bad]) > 0.97
    assert np.mean([r.predicted == r.quality for r in got]) > 0.93


def test_classifier_does_not_read_held_out_or_negative_labels(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    held = quality.held_out(F.col("doc_id"))
    other = labels.withColumn("quality", F.when(held, 1 - F.col("quality")).when(F.col("quality") == 0, 0).otherwise(F.col("quality"))).where("quality = 1 OR NOT (quality = 1)")
    a, b = (rows(quality.score(docs, quality.fit(docs, x))) for x in (labels, other.where(held | (F.col("quality") == 1))))
    assert a == b


def plain_risk(layers, xp, xu, prior):
    """The non-negative risk text by text, from its description."""
    def cost(x, label):
        hidden = [np.tanh(sum(a * b for a, b in zip(x, layers[0][:, j], strict=True)) + layers[1][j]) for j in range(len(layers[1]))]
        z = sum(a * b for a, b in zip(hidden, layers[2], strict=True)) + layers[3][0]
        return np.log1p(np.exp(-z if label else z))

    mean = lambda rows, label: sum(cost(x, label) for x in rows) / len(rows)
    if prior is None:
        return mean(xp, 1) + mean(xu, 0), 1.0
    rest = mean(xu, 0) - prior * mean(xp, 0)
    return prior * mean(xp, 1) + max(0.0, rest), rest


@pytest.mark.parametrize("prior", [None, 0.3, 0.95])
def test_risk_and_gradient(prior):
    rng = np.random.default_rng(6)
    xp, xu = rng.normal(1, 1, (7, 4)), rng.normal(-1, 1, (9, 4))
    layers = [rng.normal(0, 1, (4, 3)), rng.normal(0, 1, 3), rng.normal(0, 2, 3), np.array([0.3])]
    if prior == 0.95:  # positives that look like negatives: the negatives' part falls below zero
        xp = xu[:7] + 0.1
        layers[2] = -np.abs(layers[2])
        layers[3] = np.array([3.0])
    value, grads = quality.risk(layers, xp, xu, prior)
    want, rest = plain_risk(layers, xp, xu, prior)
    assert abs(value - want) < 1e-9

    def moved(k, i, by, part):
        other = [x.copy() for x in layers]
        other[k].flat[i] += by
        return plain_risk(other, xp, xu, prior)[part]

    undone = prior is not None and rest < 0
    for k, grad in enumerate(grads):
        for i in range(grad.size):
            numeric = (moved(k, i, 1e-5, int(undone)) - moved(k, i, -1e-5, int(undone))) / 2e-5
            assert abs(grad.flat[i] - (-numeric if undone else numeric)) < 1e-6


def test_prior_estimate():
    rng = np.random.default_rng(1)
    pos, unl = rng.normal(2, 1, 4000), np.concatenate([rng.normal(2, 1, 2800), rng.normal(-3, 1, 1200)])
    assert abs(quality.estimate_prior(pos, unl) - 0.7) < 0.06


def test_classifier_on_odd_and_empty_tables(spark, odd, none, docs):
    network = quality.fit(none, none.selectExpr("doc_id", "1 AS quality"))
    assert {r.score for r in quality.score(odd, network).collect()} == {0.5}
    assert quality.score(none, network).count() == 0
    assert quality.keep_good(odd, network, 0.9).count() == 2 and quality.keep_good(none, network).columns == odd.columns


# lines


def test_templates_generalise_and_first_copies_stay(spark, none, odd):
    text = lambda *lines: "\n".join(lines)
    boiler = "Copyright by the masked publisher of this very site in 2024 for all of its readers"
    field = "Order of the customer named {} was shipped to the place that was asked for"
    data = [
        (1, text(boiler, "only here and nowhere else at all", field.format("anna"))),
        (2, text("its own line of words stays", boiler.replace("2024", "1999"), "", field.format("bert"))),
        (3, text(boiler, field.format("carl"))), (4, "short line"), (5, "short line"), (6, None), (7, ""), (8, text("twice within one document", "twice within one document")),
        (None, boiler), (9, "Order of the customer with quite other words that nobody else uses in any line here ok"),
    ]
    df = spark.createDataFrame([(i, t, len(t or "")) for i, t in data], "doc_id bigint, text string, n_chars bigint")
    got = {r.doc_id: r for r in line_templates.drop_recurring(df, report=True).collect()}
    assert got[1].text == data[0][1] and got[1].n_dropped == 0
    assert got[2].text == "its own line of words stays\n" and got[2].n_dropped == 2
    assert got[3].text == "" and got[3].n_lines == 2
    assert (got[4].text, got[5].text, got[6].text, got[7].text, got[8].n_dropped, got[None].text) == ("short line", "short line", None, "", 0, boiler)
    assert got[9].n_dropped == 0
    kept = line_templates.drop_recurring(df)
    assert kept.columns == df.columns and {r.doc_id for r in kept.collect()} == {1, 2, 4, 5, 6, 7, 8, 9, None}
    assert {r.doc_id: r.n_chars for r in kept.collect()}[2] == len("its own line of words stays\n")
    assert line_templates.drop_recurring(none).count() == 0
    out = line_templates.drop_recurring(odd)
    assert out.columns == odd.columns and {r.doc_id for r in odd.collect()} - {r.doc_id for r in out.collect()} == {6}


def test_like_lines_of_many_variants(spark, none, odd):
    field = "Order of the customer {} of {} was shipped to the place that was asked for"
    edited = "Copyright by the {} publisher of this {} site for all {} its many readers here".format
    held = [field.format(n, c) for n in ("anna", "bert") for c in ("rome", "bonn")] + [edited("masked", "very", "of"), edited("other", "very", "of"), edited("masked", "new", "of"), edited("masked", "very", "by")]
    held += ["Copyright by the quite other words that nobody else uses in any line here ok", "one two three four fife", "one two three four five"]
    df = spark.createDataFrame(list(enumerate(held)), "doc_id bigint, text string")
    got = line_templates.drop_recurring(df, report=True, by=line_templates.like_lines).collect()
    assert {r.doc_id for r in got if r.n_dropped} == {1, 2, 3, 5, 6, 7, 10}
    assert line_templates.drop_recurring(none, by=line_templates.like_lines).count() == 0


def test_like_lines_in_parts_of_a_band_and_hot_templates(spark, odd, monkeypatch):
    rng = np.random.default_rng(9)
    middle = "in the very middle of it all"
    held = [f"all begin so {a} {b} {c} {middle} {d} {e} {f} {g}" for a, b, c, d, e, f, g in rng.integers(0, 10, (300, 7)).astype(str)]
    held = [" ".join("abcdefghij"[int(w)] if w.isdigit() else w for w in x.split()) for x in held]
    df = spark.createDataFrame(list(enumerate(held)), "doc_id bigint, text string").withColumns({"_id": F.lit(1), "_LOST": F.lit("x"), "_kept": F.lit(2)})
    want = {i for i, x in enumerate(held) if any(5 * sum(p == q for p, q in zip(x.split(), y.split(), strict=True)) >= 4 * len(x.split()) for y in held[:i])}
    for block, hot in ((1000, 10**6), (7, 0)):
        monkeypatch.setattr(line_templates, "BLOCK", block)
        monkeypatch.setattr(line_templates, "HOT", hot)
        got = line_templates.drop_recurring(df, by=line_templates.like_lines)
        assert {r.doc_id for r in got.collect()} == set(range(300)) - want and got.columns == df.columns
    assert 50 < len(want) < 290
    out = line_templates.drop_recurring(odd, by=line_templates.like_lines)
    assert out.columns == odd.columns


def test_like_lines_are_those_of_all_pairs(spark):
    rng = np.random.default_rng(7)
    data = []
    for i in range(400):
        n = int(rng.integers(3, 24))
        words = ["a", "b", "c", *(f"{'xyz'[i % 3]}{chr(97 + k)}" for k in range(21))][:n]
        for k in rng.integers(0, n, int(rng.integers(0, n // 4 + 2))):
            words[k] = "pqrs"[int(rng.integers(0, 4))]
        data.append((i, words))
    want = {i for i, w in data if any(v[:3] == w[:3] and len(v) == len(w) and 5 * sum(x == y for x, y in zip(v, w, strict=True)) >= 4 * len(w) for _, v in data[:i])}
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in data], "doc_id bigint, text string")
    got = line_templates.drop_recurring(df, report=True, by=line_templates.like_lines).where("n_dropped > 0").collect()
    assert {r.doc_id for r in got} == want and 20 < len(want) < 390


def test_like_lines_of_every_length_and_script(spark, odd):
    han, tabs = "\u4e2d\u6587\u5b57\u7b26" * 9, "one\ttwo three\u00a0four five"
    held = ["Short.", "Short.", "Page 1", "Page 2", "12", "77", "12", han, han, han[:9] + "2024", han[3:12] + "2024", tabs, "one two  three four five\r", "one two three four five", "one two three four six", "\t \u3000", "\t \u3000"]
    df = spark.createDataFrame(list(enumerate(held)), "doc_id bigint, text string")
    got = line_templates.drop_recurring(df, report=True, by=line_templates.like_lines).collect()
    assert {r.doc_id for r in got if r.n_dropped} == {1, 3, 6, 8, 12, 13, 14}
    con = duckdb.connect()
    for table in (df, odd.select("doc_id", "text")):
        con.register("documents", table.toPandas().astype({"doc_id": "Int64"}))
        want = Counter(con.sql(line_templates.LIKE_SQL).fetchall())
        assert Counter(map(tuple, line_templates.drop_recurring(table, report=True, by=line_templates.like_lines).collect())) == want


# placement


def test_table_is_full_even_and_stable():
    names = shard_table.shard_names(16)
    owner = shard_table.fill(names, 4099)
    counts = Counter(owner)
    assert set(counts) == set(range(16)) and max(counts.values()) - min(counts.values()) <= 1
    fewer = shard_table.fill(names[:-1], 4099)
    assert sum(a != b for a, b in zip(owner, fewer, strict=True) if a != 15) < 0.2 * 4099
    weighted = Counter(shard_table.fill(names[:2], 101, [3, 1]))
    assert weighted[0] > 2.5 * weighted[1]
    for bad in (([], 7), (names, 10), (names, 7)):
        with pytest.raises(ValueError):
            shard_table.fill(*bad)


def test_placement(spark, odd, none, tmp_path):
    placed = shard_table.place(odd)
    assert placed.count() == odd.count() and placed.where("shard IS NULL").count() == 0 and shard_table.place(none).count() == 0
    assert rows(placed.groupBy("doc_id").agg(F.count_distinct("shard").alias("n")).where("n > 1")) == []
    plan = placed._jdf.queryExecution().toString()
    assert "BroadcastHashJoin" in plan and "Python" not in plan and "ExistingRDD" not in shard_table.place(spark.range(9), "id")._jdf.queryExecution().toString()
    hot = spark.range(3000).select(F.lit(7).alias("k"), "id")
    assert shard_table.place(hot, "k").select("shard").distinct().count() == 1 and shard_table.place(hot, "k", salt="id").select("shard").distinct().count() == 16
    shard_table.write_sharded(spark.range(500), str(tmp_path / "out"), key="id")
    assert placed.columns[1:] == [*(f"own_{c}" if c in ("slot", "shard") else c for c in odd.columns), "shard"] and {(r.own_slot, r.own_shard) for r in placed.collect()} == {(7, "x")}
    for df in (odd, none):  # whole rows, from the files
        got = Counter((r.doc_id, r.shard, r.text_md5) for r in shard_table.store_and_read(df).collect())
        md5 = lambda t: None if t is None else hashlib.md5(t.encode()).hexdigest()
        assert got == Counter((r.doc_id, r.shard, md5(r.text)) for r in shard_table.place(df).collect())
    shard_table.write_sharded(hot, str(tmp_path / "hot"), "k", rows_per_file=10)
    sizes = spark.read.parquet(str(tmp_path / "hot")).groupBy(F.input_file_name()).count().collect()
    assert len(sizes) > 3 and sum(r["count"] for r in sizes) == 3000
    back = spark.read.parquet(str(tmp_path / "out"))
    assert back.count() == 500 and abs(shard_table.share_table(back).agg(F.sum("share")).first()[0] - 1) < 1e-9


# digests


def plain_digest(data: bytes) -> str:
    """The digest from its description, a triplet and a bucket at a time."""
    counts = [0] * 256
    for k, (_, j, m) in enumerate(((0, 1, 2), (0, 3, 7), (0, 5, 11), (0, 8, 17))):
        for i in range(len(data) - m):
            h = ((data[i] << 16 | data[i + j] << 8 | data[i + m]) * 2654435761 + 40503 * k) % 2**32
            h = (h ^ h >> 15) * 2246822519 % 2**32
            counts[h >> 24] += 1
    q1, q2, q3 = (sorted(counts)[n] for n in (63, 127, 191))
    quartile = [sum(c > q for q in (q1, q2, q3)) for c in counts]
    length = min(255, round(8 * np.log2(1 + len(data))))
    part = lambda q: min(15, 16 * q // max(1, q3))
    head = [hashlib.blake2b(data, digest_size=1).digest()[0], length, part(q1) * 16 + part(q2)]
    body = [sum(x * 4 ** (3 - i) for i, x in enumerate(quartile[at : at + 4])) for at in range(0, 256, 4)]
    return bytes(head + body).hex()


def plain_likeness(x: str, y: str) -> float:
    a, b = bytes.fromhex(x), bytes.fromhex(y)
    if a == b:
        return 1.0
    score = int(a[0] != b[0]) + 2 * min(12, abs(a[1] - b[1])) + min(4, abs(a[2] // 16 - b[2] // 16)) + min(4, abs(a[2] % 16 - b[2] % 16))
    for p, q in zip(a[3:], b[3:], strict=True):
        for s in (1, 4, 16, 64):
            d = abs(p // s % 4 - q // s % 4)
            score += 6 if d == 3 else d
    return max(0.0, 1 - score / (1.3 * 256))


def test_digest_and_likeness_are_the_plain_ones(odd, docs):
    rng = np.random.default_rng(4)
    held = [(r.text or "").encode() for r in [*odd.collect(), *docs.limit(40).collect()]] + [b"", b"ab", bytes(2000), rng.bytes(3000), rng.bytes(200_000), b"ab" * 50_000]
    prints = [digest.fingerprint(x) for x in held]
    assert prints == [plain_digest(x) for x in held]
    assert all(abs(digest.likeness(x, y) - plain_likeness(x, y)) < 1e-12 for x in prints for y in prints)
    near = [bytes.fromhex(digest.fingerprint(rng.bytes(400_000)))[2] for _ in range(4)]  # nearly equal quartiles: high parts, none that starts again at 0
    assert min(x & 15 for x in near) >= 14


def test_digest_of_edits_and_neighbours(odd, docs, none):
    for df in (odd, docs, none, odd.where("doc_id = 4")):
        held = pairs(df.select("doc_id", "text").collect())
        got = sorted((r for r in digest.compare_with_next(df).collect()), key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.n_chars))
        assert len(got) == len(held)
        if df is odd:
            continue  # its repeated id is ordered by a hash
        for k, (r, (doc_id, text)) in enumerate(zip(got, held, strict=True)):
            following = held[(k + 1) % len(held)][1]
            q = len(text) // 4
            edited = text[: len(text) - q] + following[:q]
            assert (r.doc_id, r.n_chars, r.edited_sha256) == (doc_id, len(text), hashlib.sha256(edited.encode()).hexdigest())
            own, changed = plain_digest(text.encode()), plain_digest(edited.encode())
            assert r.fingerprint == own and r.edited_fingerprint == changed and (text != following or r.near_next == 1)
            assert abs(r.near_edited - plain_likeness(own, changed)) < 1e-12 and abs(r.near_next - plain_likeness(own, plain_digest(following.encode()))) < 1e-12


def test_digest_tells_edits_from_other_documents(docs):
    got = digest.compare_with_next(docs.where("n_chars > 400").dropDuplicates(["text"])).collect()
    assert np.mean([r.near_edited for r in got]) > np.mean([r.near_next for r in got]) + 0.3
    assert digest.difference(got[0].fingerprint, got[0].fingerprint) == 0


# near duplicates


def brute(held, words, percent=80):
    sets = defaultdict(set)
    for doc_id, text in held:
        w = "".join(c.lower() if "A" <= c <= "Z" else c for c in text).encode().split()
        if w and doc_id is not None:
            k = min(words, len(w))
            sets[doc_id] |= {tuple(w[i : i + k]) for i in range(len(w) - k + 1)}
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {d: find(d) for d in parent}, {d: len(s) for d, s in sets.items()}


@pytest.mark.parametrize("words", [2, 5])
def test_near_duplicates_are_brute_force_ones(odd, docs, none, words):
    for df in (docs, odd, none):
        held = pairs(df.select("doc_id", "text").collect())
        roots, sizes = brute(held, words)
        got = near_dup.near_duplicates(df, words=words).collect()
        assert len(got) == len(held)
        for r in got:
            assert (r.component_id, r.n_shingles) == (roots.get(r.doc_id, r.doc_id), sizes.get(r.doc_id, 0 if r.doc_id is not None else r.n_shingles))
            assert r.kept == (r.doc_id is None or r.doc_id == r.component_id)


def test_least_shared_values():
    rng = np.random.default_rng(3)
    for n in (1, 2, 9, 60, 102):
        assert near_dup.least_shared(n, 80) == -(-80 * n // 100)  # no set that is linked with one of these has a union beyond K
    found = [near_dup.least_shared(n, 80) for n in (130, 200, 400, 5000, 10**6)]
    assert found == sorted(found, reverse=True) and found[-1] > 55
    for union in (250, 2000):
        shared = -(-80 * union // 100)
        draws = rng.hypergeometric(shared, union - shared, near_dup.K, 200_000)
        assert draws.min() >= near_dup.least_shared(union * 80 // 100, 80)


def test_links_of_long_texts_are_brute_force_ones(spark):
    """Sets beyond a sketch: pairs on both sides of the threshold, and as many far from it."""
    rng = np.random.default_rng(11)
    data, at = [], 0
    for size in (90, 125, 150, 400, 1500):
        for edits in (0.02, 0.1, 0.11, 0.115, 0.12, 0.2):
            words = [f"{size}-{edits}-{k}" for k in range(size)]
            for _ in range(6):
                changed = list(words)
                for k in rng.choice(size, int(edits * size), replace=False):
                    changed[k] = f"x{at}-{k}"
                data.append((at, " ".join(changed)))
                at += 1
    df = spark.createDataFrame(data, "doc_id bigint, text string")
    for words in (1, 2):
        roots, _ = brute(data, words)
        assert {r.doc_id: r.component_id for r in near_dup.near_duplicates(df, words=words).collect()} == roots
        assert 5 < len(set(roots.values())) < len(data)


def by_rows(held, words, percent=80):
    """Components where rows of one id are one document, linked by each of its texts."""
    alone = [(i, t) for i, (_, t) in enumerate(held)]
    roots, _ = brute(alone, words, percent)
    link = {}
    for i, (doc_id, _) in enumerate(held):
        link.setdefault(("set", roots.get(i, i)), set()).add(doc_id)
    parent = {d: d for d, _ in held}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for ids in link.values():
        low = min(map(find, ids))
        for x in ids:
            parent[find(x)] = low
    return {d: find(d) for d in parent}


def test_documents_with_several_texts(spark):
    a, b = ([f"{c}{k}" for k in range(40)] for c in "ab")
    near = lambda words, k: " ".join(w if i != k else "other" for i, w in enumerate(words))
    held = [(1, " ".join(a)), (1, " ".join(b)), (2, near(b, 3)), (3, near(a, 5)), (4, "alone here"), (4, ""), (7, "quite another text"), (6, "alone here"), (6, "quite another text"), (5, None), (8, ""), (8, " ".join(f"z{k}" for k in range(30)))]
    for order in (held, held[::-1]):
        df = spark.createDataFrame(order, "doc_id bigint, text string")
        got = near_dup.near_duplicates(df, words=2).collect()
        assert len(got) == len(held)
        assert {r.doc_id: r.component_id for r in got if r.n_shingles} == {1: 1, 2: 1, 3: 1, 4: 4, 6: 4, 7: 4, 8: 8}
        assert {r.doc_id: r.component_id for r in got if r.n_shingles} == {k: v for k, v in by_rows([(d, t) for d, t in held if t], 2).items()}
        assert {r.doc_id for r in near_dup.keep_one(df, words=2).collect()} == {1, 4, 5, 8}


def test_long_list_of_unlinked_members(spark):
    """A value that 20,000 sets hold and that is as rare as all others: no task holds the list, and no pair is emitted that
    the sizes, places and maps rule out."""
    n = 20_000
    data = spark.range(n).selectExpr("id AS doc_id", "concat('shared words here ', concat_ws(' ', transform(sequence(0, 3 + cast(id % 5 as int)), k -> concat('u', id, '-', k)))) AS text")
    twins = spark.range(0, n, 500).selectExpr("id + 1000000 AS doc_id", "concat('shared words here ', concat_ws(' ', transform(sequence(0, 3 + cast(id % 5 as int)), k -> concat('u', id, '-', k)))) AS text")
    got = near_dup.near_duplicates(data.unionByName(twins), words=2)
    assert got.where("component_id <> doc_id").select("doc_id", "component_id").exceptAll(spark.range(0, n, 500).selectExpr("id + 1000000", "id")).isEmpty()
    assert got.where("NOT kept").count() == n // 500
    posted = spark.range(4000).selectExpr("CAST(7 AS BIGINT) AS v", "id AS cls", "CAST((60 << 20) + (30 << 10) + 20 AS BIGINT) AS h")
    star = near_dup._star(posted)
    classes = posted.select("cls", *[F.expr(f"xxhash64(cls, {k})").alias(f"o{k}") for k in range(near_dup.PARITY)])
    roots = spark.createDataFrame([(0, 0)], "node bigint, root bigint")
    pairs = near_dup._unjoined(near_dup._rooted(star, roots), classes, 80)
    assert pairs.count() < 4000 * 4000 / 2000  # unlike maps: few of eight million pairs are left
    plan = pairs._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan


def test_chains_and_hot_groups(spark):
    rng = np.random.default_rng(5)
    base = [f"w{i}" for i in range(60)]
    data, current = [], list(base)
    for i in range(40):  # a chain: each is near the one before, ends are far apart
        data.append((i, " ".join(current)))
        current = list(current)
        current[(i * 7) % 60] = f"n{i}"
    for i in range(300):  # a group around one text, and texts a little alike
        words = [f"g{j}" for j in range(50)]
        for j in rng.integers(0, 50, i % 12):
            words[j] = f"e{i}-{j}"
        data.append((1000 + i, " ".join(words)))
    df = spark.createDataFrame(data, "doc_id bigint, text string")
    for words in (1, 2):
        roots, _ = brute(data, words)
        assert {r.doc_id: r.component_id for r in near_dup.near_duplicates(df, words=words).collect()} == roots
    kept = near_dup.keep_one(df.withColumn("extra", F.lit(1)), words=2)
    assert kept.columns == ["doc_id", "text", "extra"] and {r.doc_id for r in kept.collect()} == {d for d, r in brute(data, 2)[0].items() if d == r}


# media


def test_images_round_trip():
    rng = np.random.default_rng(2)
    for shape in ((1, 1), (13, 64), (5, 7, 3), (9, 3)):
        x = rng.integers(0, 256, shape, np.uint8)
        assert (media.decode(media.encode_netpbm(x)) == x).all() and (media.decode(media.encode_bmp(x)) == x).all()
    assert (media.decode(b"P1\n# note\n3 2\n1 0 1\n0 1 0\n") == [[0, 1, 0], [1, 0, 1]]).all()
    assert (media.decode(b"P2 2 1 255\n7 9\n") == [[7, 9]]).all() and media.decode(b"P5 1 1 65535\n\x01\x02")[0, 0] == 258
    assert (media.decode(b"P4\n3 1\n\xa0") == [[0, 1, 0]]).all() and media.decode(b"P3 1 1 255 1 2 3").tolist() == [[[1, 2, 3]]]


DAMAGED = [
    b"", b"P9", b"BM", b"P5 99999999999999999999 1 255", b"P5 0 0 255\n", b"P5 -1 1 255\nx", b"P5 2 2 255\nabc", b"P2 2 1 255\n7 300\n", b"P2 1 1 100\nx", b"P1 2 1\n0 7", b"P5 1 1 0\n0", b"P5 1 1 70000\n00",
    b"P6 1", b"P5 1 1 9\n\x0a", media.encode_bmp(np.zeros((4, 4), np.uint8))[:-1], media.encode_bmp(np.zeros((4, 4, 3), np.uint8))[:40], media.encode_bmp(np.zeros((2, 2), np.uint8)).replace(b"BM", b"BX"),
]


def test_damaged_images_are_null(spark, none):
    for bad in DAMAGED:
        with pytest.raises(ValueError):
            media.decode(bad)
    bent = bytearray(media.encode_bmp(np.full((2, 2), 9, np.uint8)))
    bent[46:50] = (4).to_bytes(4, "little")  # a palette of four colours, and a pixel of number nine
    flat = bytearray(media.encode_bmp(np.zeros((2, 2, 3), np.uint8)))
    flat[18:22] = (-2).to_bytes(4, "little", signed=True)
    held = [*DAMAGED, bytes(bent), bytes(flat), None]
    df = spark.createDataFrame([(i, x, 1, b"t") for i, x in enumerate(held)] + [(None, media.encode_netpbm(np.zeros((2, 3), np.uint8)), 1, b"t")], "doc_id bigint, media binary, height int, tile binary")
    got = media.describe(df).collect()
    assert len(got) == len(held) + 1 and {(r.height, r.width, r.tile, r.difference_hash) for r in got if r.doc_id is not None} == {(None,) * 4}
    assert [(r.height, r.width) for r in got if r.doc_id is None] == [(2, 3)] and media.describe(df.where("false")).count() == 0


def test_area_resize_keeps_means():
    x = np.arange(12 * 20, dtype=np.float64).reshape(12, 20)
    assert np.allclose(media.area_resize(x, 12, 20), x) and np.allclose(media.area_resize(x, 6, 5), x.reshape(6, 2, 5, 4).mean((1, 3)))
    assert np.isclose(media.area_resize(x, 7, 3).mean(), x.mean())
    assert np.load(__import__("io").BytesIO(media.npy_tile(x))).shape == (32, 32) and len(media.difference_hash(x)) == 16


def plain_hash(x: np.ndarray) -> str:
    """The difference hash from sums over whole and part samples, cell by cell."""
    h, w = x.shape
    share = lambda lo, hi, i: max(0.0, min(hi, i + 1) - max(lo, i))
    rows = np.array([[share(r * h / 8, (r + 1) * h / 8, i) for i in range(h)] for r in range(8)])
    cells = np.array([[share(c * w / 9, (c + 1) * w / 9, j) for j in range(w)] for c in range(9)])
    small = np.round(rows @ x.astype(np.float64) @ cells.T / (h / 8 * w / 9), 6)
    bits = "".join("1" if small[r, c] < small[r, c + 1] else "0" for r in range(8) for c in range(8))
    return f"{int(bits, 2):016x}"


def test_media_query(spark, odd, docs, none):
    for df in (odd, docs, none):
        want = Counter()
        for r in df.collect():
            raw = (r.text or "").encode()
            full = raw + bytes(max(64, -(-len(raw) // 64) * 64) - len(raw))
            image = b"P5\n64 %d\n255\n" % (len(full) // 64) + full
            want[r.doc_id, len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-64:]), len(image), hashlib.sha256(image).hexdigest()] += 1
        assert Counter(tuple(r)[:7] for r in media.store_and_describe(df).collect()) == want
    for df in (odd, docs, none):  # both forms, and tiles that were written and read back
        got = media.store_and_describe(df, media.BOTH).collect()
        assert len(got) == df.count()
        texts = Counter((r.doc_id, r.text or "") for r in df.collect())
        want = Counter()
        for (doc_id, text), n in texts.items():
            x = np.frombuffer(media.payload(text), np.uint8).reshape(-1, 64)
            image = (media.encode_bmp if len(x) % 2 else media.encode_netpbm)(x)
            tile = media.npy_tile(x)
            want[doc_id, hashlib.sha256(x.tobytes()).hexdigest(), hashlib.sha256(image).hexdigest(), plain_hash(x), hashlib.sha256(tile).hexdigest()] += n
        assert Counter((r.doc_id, r.payload_sha256, r.media_sha256, r.feature, r.tile_sha256) for r in got) == want
    odd_images = spark.createDataFrame([(1, media.encode_bmp(np.zeros((2, 2, 3), np.uint8))), (2, b"junk"), (3, None)], "doc_id bigint, media binary")
    assert {r.doc_id: r.channels for r in media.describe(odd_images).collect()} == {1: 3, 2: None, 3: None}


# pipeline


def test_pipeline_stages_on_odd_and_empty_tables(spark, odd, none):
    import corpus_pipeline

    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, odd, SF)
        assert out.columns == odd.columns and stage(spark, none, SF).count() == 0, name
        assert {r.doc_id for r in out.collect()} <= {r.doc_id for r in odd.collect()}
    out = corpus_pipeline.packed(spark, odd, SF)
    assert {r.doc_id for r in out.collect()} == {r.doc_id for r in odd.collect()} and corpus_pipeline.packed(spark, none, SF).count() == 0


def test_near_copies_that_the_pipeline_finds(spark):
    """Texts with a word in a hundred, in fifty or in twenty-five changed: those that the shingles link, and no others, go.
    At 0.8, five-word shingles link few of the last, two-word shingles nearly all."""
    rng, data, at = np.random.default_rng(8), [], 0
    for rate in (0.01, 0.02, 0.04):
        for _ in range(30):
            words = [f"w{k}" for k in rng.integers(0, 5000, 300)]
            data.append((at, rate, " ".join(words)))
            copy = [f"e{at}-{k}" if rng.random() < rate else w for k, w in enumerate(words)]
            data.append((at + 1, rate, " ".join(copy)))
            at += 2
    df = spark.createDataFrame([(i, t) for i, _, t in data], "doc_id bigint, text string")
    for words in (5, 2):
        roots, _ = brute([(i, t) for i, _, t in data], words)
        gone = {r.doc_id for r in near_dup.near_duplicates(df, words=words).where("NOT kept").collect()}
        assert gone == {i for i, r in roots.items() if i != r}
        found = [np.mean([i in gone for i, r, _ in data if r == rate and i % 2]) for rate in (0.01, 0.02, 0.04)]
        assert found[0] == 1 and found == sorted(found, reverse=True) and (words == 5 or found[2] > 0.9)


def test_pipeline_against_its_stages_by_hand(spark):
    import corpus_pipeline
    from progressive_text.llm.common import documents, saved

    docs = documents(spark, SF)
    network = quality.fit(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    good = [r for r in docs.collect() if not r.text or network.scores(quality.features(r.text)[None])[0] >= 0.5]
    first = corpus_pipeline.good_documents(spark, docs, SF)
    assert {r.doc_id for r in first.collect()} == {r.doc_id for r in good} and first.columns == docs.columns
    second = saved(corpus_pipeline.fresh_lines(spark, saved(first, "first"), SF), "second")
    seen = defaultdict(set)
    for r in second.collect():
        for line in set(r.text.split("\n")):
            if len(line.split(" ")) >= 3 and line.strip():
                seen[line].add(r.doc_id)
    assert all(len(ids) == 1 for ids in seen.values())
    third = corpus_pipeline.one_of_each(spark, second, SF)
    roots, _ = brute(pairs(second.select("doc_id", "text").collect()), 5)
    assert {r.doc_id for r in third.collect()} == {r.doc_id for r in second.collect() if roots.get(r.doc_id, r.doc_id) == r.doc_id}
    out = corpus_pipeline.run(spark, SF)
    assert {r.doc_id for r in out.select("doc_id").distinct().collect()} == {r.doc_id for r in third.collect()}
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_classifier", "line_dedup", "minhash_near_dedup", "best_fit_packing"]


def test_pairs_of_many_common_lists_are_made_once(spark, monkeypatch):
    """Texts that are nearly linked share dozens of lists, and each pair of them comes out of one, without a distinct."""
    rng, data = np.random.default_rng(3), []
    for family in range(3):
        base = [f"f{family}-{k}" for k in range(400)]
        for i in range(15):
            at = int(rng.integers(0, 370))
            data.append((len(data), " ".join(base[:at] + [f"x{family}-{i}-{k}" for k in range(25)] + base[at + 25 :])))
    made, plain = [], near_dup._unjoined
    monkeypatch.setattr(near_dup, "_unjoined", lambda *x: made.append((x, plain(*x))) or made[-1][1])
    df = spark.createDataFrame(data, "doc_id bigint, text string")
    got = {r.doc_id: r.component_id for r in near_dup.near_duplicates(df, words=2).collect()}
    assert got == brute(data, 2)[0]
    (rooted, classes, percent), pairs = made[0]
    rows = [(r.a, r.b) for r in pairs.collect()]
    assert len(rows) == len(set(rows)) > 20 and "HashAggregate" not in pairs._jdf.queryExecution().executedPlan().toString()
    # the pairs that any common list would make
    near = near_dup._parity(percent, near_dup._size("h"), near_dup._size("g"), "", "b_", [f"o{k}" for k in range(near_dup.PARITY)])
    odd = [f"o{k}" for k in range(near_dup.PARITY)]
    x = rooted.join(classes.select("cls", *odd), "cls").select("v", F.col("cls").alias("a"), "h", "r", "hr", *odd)
    y = rooted.join(classes.select("cls", *odd), "cls").select("v", F.col("cls").alias("b"), F.col("h").alias("g"), F.col("r").alias("s"), *[F.col(c).alias(f"b_{c}") for c in odd])
    every = x.join(y, "v").where((F.col("r") != F.col("hr")) & (F.col("r") != F.col("s")) & near_dup._possible(percent, "h", "g") & near)
    lists = every.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    assert set(rows) == {(r.a, r.b) for r in lists.collect()} and lists.count() > 5 * len(rows)
