"""Each operator against brute force on small fixtures, with nulls, empties, repeats, ties and clashing columns."""

import math
import random
import re
from collections import Counter

import duckdb
import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from rpqframe.llm import ann_forest, decontaminate, licenses, line_dedup, quote_links, registry, secrets, simhash, sp_sampling, token_count, toxicity
from rpqframe.llm.components import connected_components

SF = "/root/testdata/sf0.001"
DOCS = "doc_id bigint, text string"
ASCII_LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
ODD = [(None, "a b c"), (1, None), (2, ""), (3, "  \n "), (4, "x" * 3000), (5, "same text here"), (5, "same text here"), (6, "same text here"), (7, "é ß 漢字 \U0001f600 ▁"), (8, "\x00\x01 tab\there")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def odd(spark):
    # extra columns with the names that operators use inside
    return spark.createDataFrame([(*r, 1, 2, 3.0) for r in ODD], DOCS + ", id int, fp int, __hits double")


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


# 1 nearest neighbours


def nearest(rows, k):
    ok = {}
    for i, v in sorted(rows, key=lambda r: (r[0] is None, r[0] or 0, r[1] or [])):
        if i is not None and v and all(x is not None and math.isfinite(x) for x in v) and any(v) and i not in ok:
            ok[i] = np.array(v, float)
    out = {}
    for q in (i for i in ok if i % 50 == 0):
        s = [(-float((ok[q] * ok[i]).sum() / (np.sqrt((ok[q] ** 2).sum()) * np.sqrt((ok[i] ** 2).sum()))), i) for i in ok if i != q and len(ok[i]) == len(ok[q])]
        out[q] = [i for _, i in sorted(s)[:k]]
    return out


def test_ann_recall(spark):
    df = spark.read.parquet(f"{SF}/embeddings.parquet")
    got = {}
    for r in ann_forest.search(df, lambda i: i % 50 == 0).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append(r.vec_id)
    want = nearest([(r.vec_id, list(r.embedding)) for r in df.collect()], 5)
    assert got.keys() == want.keys() and sum(len(set(got[q]) & set(want[q])) for q in want) >= 0.9 * 5 * len(want)


def test_ann_odd_rows(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [1.0, 0.0]), (3, [0.0, 1.0]), (50, [0.0, 0.0]), (100, [nan, 1.0]), (150, None), (200, [inf, 1.0]), (250, []), (300, [None, 1.0]), (350, [1.0, 2.0, 3.0]), (None, [1.0, 1.0]), (3, [0.0, 1.0]), (400, [0.0, -1.0])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got = {}
    for r in ann_forest.search(df, lambda i: i % 50 == 0, share=24.0).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append(r.vec_id)
    assert got == {0: [1, 2, 3, 400], 400: [0, 1, 2, 3]}
    assert ann_forest.search(df.where("false"), lambda i: i % 50 == 0).count() == 0


def test_forest_ascends_until_enough():
    x = np.random.default_rng(1).standard_normal((400, 16))
    f = ann_forest.Forest(x, trees=6)
    for c in f.candidates(x[:20], 100):
        assert len(c) >= 100 / 6
    assert all(k in c for k, c in enumerate(f.candidates(x[:20], 1)))


# 2 lines


def one_edit(a, b):
    if abs(len(a) - len(b)) > 1:
        return False
    a, b = sorted((a, b), key=len)
    i = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), len(a))
    return a[i + 1 :] == b[i + 1 :] if len(a) == len(b) else a[i:] == b[i + 1 :]


def brute_lines(rows):
    lines = sorted({(i, k, x.strip(" ")) for i, t in rows if i is not None and t for k, x in enumerate(t.split("\n")) if x.strip(" ")})
    first, exact, near = {}, set(), set()
    for i, k, x in lines:
        if x in first:
            exact.add((i, k))
        else:
            first[x] = (i, k)
    ordered = sorted((p, x) for x, p in first.items() if len(x) >= 16)
    for n, (p, x) in enumerate(ordered):
        if any(one_edit(x, y) for _, y in ordered[:n]):
            near.add(p)
    return exact, near


def test_lines(spark):
    r = random.Random(4)
    base = ["The quick brown fox jumps over", "Template line number here", "x" * 20, "abababababababab", "漢字かな交じり文の行はここにありますよ", "short", " ".join(f"word{k}" for k in range(40))]
    rows = list(ODD)
    for i in range(10, 50):
        out = []
        for _ in range(6):
            t = r.choice(base)
            for _ in range(r.randint(0, 2)):
                k, c = r.randint(0, len(t)), r.choice("xyé9")
                t = r.choice([t[:k] + c + t[k:], t[:k] + t[k + 1 :], t[:k] + c + t[k + 1 :]])
            out.append(t)
        rows.append((i, "\n".join(out)))
    rows.append(rows[-1])
    df = spark.createDataFrame([(*x, 0, 0, 0) for x in rows], DOCS + ", id int, _id int, _hit int")
    exact, near = brute_lines(rows)
    got = line_dedup.line_decisions(df).collect()
    assert {(x.id, k) for x in got for k in x.exact} == exact and {(x.id, k) for x in got for k in x.near} == near and near
    kept = line_dedup.dedup_lines(df)
    assert kept.columns == df.columns
    texts = {x.doc_id: x.text for x in kept.collect()}
    assert texts[1] is None and texts[2] == "" and None in texts and texts[3] == "  \n "
    for i, t in rows:
        if i is not None and i >= 10:
            left = "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in exact | near)
            assert texts.get(i, "") == left


def test_block_variants_meet():
    r = random.Random(12)
    for _ in range(4000):
        a = "".join(r.choice("ab") for _ in range(r.randint(0, 60)))
        k = r.randint(0, len(a))
        b = r.choice([a[:k] + "c" + a[k:], a[:k] + a[k + 1 :], a[:k] + "c" + a[k + 1 :]])
        common = {x[0] for x in line_dedup.block_keys(7, a)} & {x[0] for x in line_dedup.block_keys(7, b)}
        assert common, (a, b)


def test_lines_of_nothing(none):
    assert line_dedup.dedup_report(none).count() == 0 and line_dedup.dedup_lines(none).count() == 0


# 3 quotes


def test_quotes(spark):
    rows = [
        (1, 0, "Hello there my friend\nhow are you doing"), (1, 1, "> Hello there my  FRIEND\nfine thanks and you too"), (1, 2, ">> hello there my friend\n> fine thanks and you too\nglad to hear this"), (2, 0, "> glad to hear this\nothers say so"),
        (3, 0, "> nobody ever wrote this"), (3, 1, None), (3, 2, ""), (None, 1, "> Hello there my friend"), (4, None, "> x"), (1, 1, "> Hello there my  FRIEND\nfine thanks and you too"),
    ]
    df = spark.createDataFrame([(*x, 9) for x in rows], "conv_id bigint, turn bigint, text string, hash int")
    got = quote_links.reply_threads(df)
    assert got.count() == len(rows)
    by = {(r.conv_id, r.turn): r for r in got.collect()}
    assert [(by[k].parent_conv, by[k].parent_turn, by[k].root_turn, by[k].depth) for k in ((1, 0), (1, 1), (1, 2), (2, 0))] == [(None, None, 0, 0), (1, 0, 0, 1), (1, 1, 0, 2), (1, 2, 0, 3)]
    assert by[1, 2].own_text == "glad to hear this" and by[1, 2].n_quoted == 2 and by[3, 0].parent_conv is None and by[3, 0].n_linked == 0
    assert quote_links.reply_threads(df.where("false")).count() == 0
    roles = df.withColumn("role", F.when(F.col("turn") % 2 == 0, "user").otherwise("assistant"))
    made = {(x.root_conv, x.root_turn): [(m.conv, m.turn, m.role, m.text) for m in x.messages] for x in quote_links.conversations(roles).collect()}
    assert made == {(1, 0): [(1, 0, "user", "Hello there my friend\nhow are you doing"), (1, 1, "assistant", "fine thanks and you too"), (1, 2, "user", "glad to hear this"), (2, 0, "user", "others say so")]}
    assert sorted(len(x.messages) for x in quote_links.conversations(roles, most=3).collect()) == [1, 3]


def brute_links(rows, least=8):
    """Parents by plain search: (conv, turn) -> (number quoted, number linked, parent)."""
    norm = lambda x: re.sub(r"\s+", " ", re.sub(r"^\s*(?:>\s*)+", "", x)).lower().strip(" ")
    level = lambda x: (re.match(r"^\s*(?:>\s*)+", x) or [""])[0].count(">")
    own, quotes = {}, {}
    for c, t, text in rows:
        for x in (text or "").split("\n") if c is not None and t is not None else []:
            if len(norm(x)) >= least:
                if level(x):
                    at = quotes.setdefault((c, t), {})
                    at[norm(x)] = min(level(x), at.get(norm(x), 99))
                else:
                    own.setdefault(norm(x), set()).add((c, t))
    out = {}
    for me, lines in quotes.items():
        votes = {}
        for line, lev in lines.items():
            near = [p for p in own.get(line, ()) if p[0] == me[0] and p[1] < me[1]]
            far = min(own.get(line, ()), default=None)
            source = max(near) if near else far if far is not None and far < me else None
            n, least_lev = votes.get(source, (0, 99))
            votes[source] = (n + 1, min(lev, least_lev))
        known = {p: v for p, v in votes.items() if p is not None}
        best = max(((-v[1], v[0], p) for p, v in known.items()), default=None)
        out[me] = (len(lines), sum(v[0] for v in known.values()), best and best[2])
    return out


def test_quotes_against_plain_search(spark):
    r = random.Random(11)
    lines = [f"line number {k} of the talk" for k in range(12)] + ["short"]
    rows = [(c, t, "\n".join(r.choice(["", "> ", ">> ", "> > "]) + r.choice(lines) for _ in range(r.randint(0, 5)))) for c in range(12) for t in range(6)]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, text string")
    got = {(x.conv, x.turn): (x.n_quoted, x.n_linked, x.parent and tuple(x.parent)) for x in quote_links.find_links(df.toDF("conv", "turn", "text")).collect()}
    assert got == brute_links(rows)


# 4 decontamination


def brute_contamination(docs, items, n=13):
    out = []
    for i, t in docs:
        w, hit, found = WORDS.findall((t or "").translate(ASCII_LOW)), set(), set()
        for k, x in items:
            v = WORDS.findall((x or "").translate(ASCII_LOW))
            if k is None or not v:
                continue
            size = min(n, len(v))
            grams = {tuple(v[j : j + size]) for j in range(len(v) - size + 1)}
            for j in range(len(w) - size + 1):
                if tuple(w[j : j + size]) in grams:
                    hit |= set(range(j, j + size))
                    found.add(str(k))
        out.append((i, len(w), len(hit), len(found), decontaminate.digest(found), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=str)


def test_contamination(spark, odd):
    r = random.Random(2)
    word = lambda: r.choice(["alpha", "Beta", "gamma", "dé", "x1"])
    items = [(k, " ".join(word() for _ in range(n))) for k, n in enumerate([14, 20, 13, 3, 1, 0])] + [(None, "alpha"), (7, None), (0, "x1 x1 x1 x1 dé")]
    rows = list(ODD) + [(100 + k, ", ".join(word() for _ in range(r.randint(0, 60)))) for k in range(60)] + [(200, "start " + items[0][1].upper() + "! end")]
    df = spark.createDataFrame([(*x, 1) for x in rows], DOCS + ", hits int")
    it = spark.createDataFrame([(*x, 1) for x in items], "item_id bigint, text string, hits int")
    for size in (10**6, 3):
        got = decontaminate.contamination(df, it, max_windows=size)
        assert sorted((tuple(x) for x in got.collect()), key=str) == brute_contamination(rows, items)
    bad = sum(x[-1] for x in brute_contamination(rows, items))
    assert decontaminate.remove_contaminated(df, it).count() == len(rows) - bad
    cut = decontaminate.remove_contaminated(df, it, spans_only=True)
    assert cut.count() == len(rows)
    assert decontaminate.contamination(odd, it.where("false")).where("n_hit > 0").count() == 0


def test_contamination_sql(spark):
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.execute(registry.OP4_SQL).fetchall()
    got = registry.op4_decontaminate(spark, SF)
    assert got.columns == [d[0] for d in con.description] and sorted(map(tuple, got.collect())) == sorted(want)


# 5 token counts


def test_token_counts(spark, odd, none):
    sp = token_count.processor(token_count.model_file())
    got = token_count.count_tokens(odd)
    want = sorted((str(i), len((t or "").encode()), len(sp.encode(t or ""))) for i, t in ODD)
    assert sorted((str(x.doc_id), x.n_bytes, x.n_tokens) for x in got.collect()) == want
    assert token_count.count_tokens(none).count() == 0 and token_count.splits_before_space(token_count.model_file())


def test_resynchronised_counts_are_exact():
    sp = token_count.processor(token_count.model_file())
    r = random.Random(3)
    for _ in range(60):
        text = "".join(r.choice(["the", " ", "  ", "\n", "é", "漢", "ation", "▁", "x" * 40, " of the", "\U0001f600"]) for _ in range(r.randint(1, 300))).encode()
        assert token_count.count_long(sp, text, r.choice([16, 50, 200]), r.choice([2, 8, 32])) == len(sp.encode(text))


# 6 licenses


def test_licenses(spark, docs, odd):
    extra = spark.createDataFrame([(900, "MIT License mit-license, CC BY cc-by 4.0 and GNU  General\nPublic LICENSE v3; MIT License mit license"), (901, "SPDX-License-Identifier: Apache-2.0"), (902, "mit licenser accby")], DOCS)
    rows = docs.select("doc_id", "text").union(extra).union(odd.select("doc_id", "text"))
    ref = []
    for x in rows.collect():
        w, places, labels = WORDS.findall((x.text or "").translate(ASCII_LOW)), [], set()
        for phrase, label in licenses.BASE.items():
            p = phrase.split()
            at = [k for k in range(len(w) - len(p) + 1) if w[k : k + len(p)] == p]
            places += at
            labels |= {label} if at else set()
        ref.append((str(x.doc_id), len(w), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels))))
    got = licenses.scan(rows).collect()
    assert sorted(((str(x.doc_id), x.n_words, x.n_base, x.first_word, x.last_word, x.base_labels) for x in got), key=str) == sorted(ref, key=str)
    by = {x.doc_id: x for x in got}
    assert "apache-2.0" in by[901].labels and by[901].score == 1.0 and by[902].labels == "" and all(0 <= x.score <= 1 for x in got)
    assert all(set(filter(None, x.base_labels.split(","))) <= set(x.labels.split(",")) for x in got)


def test_license_containment(spark):
    d = licenses.scan(spark.createDataFrame([(1, "Licensed under the Apache License, Version 2.0. See also the Apache License 1.1.")], DOCS)).first().detections
    assert [(x.l, x.o) for x in d if x.s < 20] == [("apache-2.0", 1)] and any(x.l == "apache-1.1" for x in d)
    assert len(licenses.rules()) > 300 and all(not re.match(x["r"].replace("(?i)", ""), "") for x in licenses.rules())


# 7 secrets


@pytest.fixture(scope="module")
def forest(spark):
    return secrets.train_forest(secrets.rule_findings(spark))


def test_printed_trees_equal_the_model(spark):
    rows = secrets.rule_findings(spark, 20)
    model = secrets.fit_forest(rows, trees=5)
    data = secrets.feature_rows(rows).cache()
    from pyspark.ml.functions import vector_to_array

    flat = data.select("features", vector_to_array("features").alias("v")).select("features", F.struct(*[F.col("v")[k].alias(n) for k, n in enumerate(secrets.FEATURES)]).alias("f"))
    for t in model.trees:
        got = t.setPredictionCol("p").setRawPredictionCol("r").setProbabilityCol("q").transform(flat).select("p", F.expr(secrets.tree_sql(t.toDebugString)).alias("own"))
        assert got.where("p <> own").count() == 0


def test_redaction_is_by_place(spark, forest):
    key = "04dbebab91ab85687d33eeaaf9ac699e1188f962"
    texts = [f'token = "{key}" and then see commit {key} or url/{key} here', f"a password=hunterhunter1xQ; token = '{key}'", None, ""]
    df = spark.createDataFrame([(k, t, 1) for k, t in enumerate(texts)], DOCS + ", _row int")
    got = {x.doc_id: x.text for x in secrets.redact(df, forest).collect()}
    assert got[0] == f'token = "[secret]" and then see commit {key} or url/{key} here' and got[2] is None and got[3] == ""
    assert key not in got[1]
    cands = {x.doc_id: [f.m for f in x.findings] for x in secrets.scan(spark.createDataFrame([(1, "api_key=abcdefgh and PASSWORD: correcthorsebatterystaplezz x " + "a" * 50 + "123456")], DOCS), forest).collect()}
    assert cands[1] == ["abcdefgh", "correcthorsebatterystaplezz", "a" * 50 + "123456"]


def test_places_and_suppression_against_plain_search(spark):
    r = random.Random(3)
    pool = ["mit license ", "licensed under the apache license, version 2.0 ", "gnu general public license v3 ", "copyright 2020 ", "words ", "SPDX-License-Identifier: MIT\n", "this program is free software: you can redistribute it and/or modify ", "https://opensource.org/licenses/MIT "]
    texts = ["".join(r.choice(pool) for _ in range(n)) for n in (0, 1, 5, 40, 300)] + ["copyright 2020 " * 700]
    df = spark.createDataFrame(list(enumerate(texts)), DOCS)
    got = {x.doc_id: [tuple(d)[:4] for d in x.detections] for x in licenses.scan(df).collect()}
    for k, t in enumerate(texts):
        low = t.lower()
        raw = {(m.start(), m.end(), x["l"], x["o"]) for x in licenses.rules() for m in re.finditer(x["r"], low)}
        inside = lambda d, x: x[0] <= d[0] and x[1] >= d[1] and x[3] <= d[3] and (x[1] - x[0] > d[1] - d[0] or x[3] < d[3])
        want = sorted(d for d in raw if not any(inside(d, x) for x in raw)) if len(raw) < 3000 else None
        assert want is None or got[k] == want, k
    assert len(got[5]) == 700


def test_forest_separates_unseen_kinds(spark):
    rows = secrets.rule_findings(spark, 40).withColumn("kind", F.col("before"))
    other = rows.where(F.col("kind").isin("with ", "sha256 = ", "secret: '", "file ", "page ", "access key "))
    trained = secrets.train_forest(rows.join(other.select("kind").distinct(), "kind", "left_anti").drop("kind"))
    docs = other.withColumn("doc_id", F.monotonically_increasing_id()).select("doc_id", F.concat("before", "candidate", F.lit(" end")).alias("text"), "label")
    got = secrets.scan(docs, trained).join(docs, "doc_id").withColumn("hit", (F.size("secrets") > 0).cast("double"))
    right = got.where("hit = label").count() / got.count()
    print("kinds not trained on:", right)
    assert right >= 0.6


def test_forest_separates_unseen_findings(spark, forest):
    # ids beyond those of the training rows, so no finding is seen before
    rows = secrets.rule_findings(spark, 150).withColumn("i", F.monotonically_increasing_id())
    rows = rows.join(secrets.rule_findings(spark).select("before", "candidate"), ["before", "candidate"], "left_anti")
    docs = rows.select(F.col("i").alias("doc_id"), F.concat("before", "candidate", F.lit(" end")).alias("text"), "label")
    got = secrets.scan(docs, forest).join(docs, "doc_id").withColumn("hit", (F.size("secrets") > 0).cast("double"))
    assert got.where("hit = label").count() >= 0.95 * got.count()


def test_secrets(spark, forest, odd):
    key = "04dbebab91ab85687d33eeaaf9ac699e1188f962"
    rows = [(1, f'see token = "{key}" here'), (2, "commit 04dbebab91ab85687d33eeaaf9ac699e1188f962 was fine"), (3, "call 4785380592391139"), (4, "see /docs/project/v12/index.html now")]
    df = spark.createDataFrame(rows, DOCS).union(odd.select(F.col("doc_id") + 100, "text"))
    by = {x.doc_id: x for x in secrets.scan(df, forest).collect()}
    assert [(s.s, s.e, s.m) for s in by[1].secrets] == [(13, 53, key)] and not by[2].secrets and not by[3].secrets and not by[4].secrets
    assert len(by[2].findings) == 1 and by[107].findings == []
    assert {x.doc_id: x.text for x in secrets.redact(df, forest).collect()}[1] == 'see token = "[secret]" here'


# 8 sampled segmentations


def test_round_trip_and_distinct(spark, odd, docs, none):
    df = docs.select(F.col("doc_id") + 1000, "text").limit(60).toDF("doc_id", "text").union(odd.select("doc_id", "text"))
    got = sp_sampling.sample_report(df, k=3).collect()
    assert all(x.decodes and len(set(x.ids_hash)) == x.n_samples for x in got) and len(got) == df.count()
    same = [x.ids_hash for x in got if x.doc_id == 5]
    assert len(same) == 2 and same[0] == same[1]
    assert {x.doc_id: x.n_samples for x in got}[2] == 1
    text = sp_sampling.sample_segmentations(df, k=1).withColumn("ids", F.col("samples")[0]["ids"])
    back = {x.doc_id: x.out for x in sp_sampling.decode_ids(text, "ids", "out").collect()}
    assert back[5] == "same text here"
    assert sp_sampling.sample_report(none).count() == 0
    assert sp_sampling.decode(sp_sampling.encode(["a b", ""])) == ["a b", ""]
    ids = {x.doc_id: x.ids for x in sp_sampling.encode_texts(odd.select("doc_id", "text")).collect()}
    assert ids[1] is None and ids[2] == [] and ids[5] == sp_sampling.encode(["same text here"])[0]


def test_report_encodes_and_decodes(spark, odd, docs):
    df = docs.select(F.col("doc_id") + 1000, "text").limit(60).toDF("doc_id", "text").union(odd.select("doc_id", "text"))
    counts = sorted((x.doc_id is not None, x.doc_id or 0, x.n_tokens) for x in token_count.count_tokens(df).collect())
    got = sp_sampling.sample_report(df).collect()
    assert sorted((x.doc_id is not None, x.doc_id or 0, x.n_tokens) for x in got) == counts and all(x.tokens_decode for x in got)
    ids = np.array(sp_sampling.encode(["same text here"])[0], dtype="<i4")
    assert {x.token_hash for x in got if x.doc_id == 5} == {xxhash.xxh64_hexdigest(ids.tobytes())}


def test_batching_does_not_matter(spark, docs):
    a = {x.doc_id: x.ids_hash for x in sp_sampling.sample_report(docs).collect()}
    b = {x.doc_id: x.ids_hash for x in sp_sampling.sample_report(docs.repartition(7)).collect()}
    assert a == b


def test_distribution_is_that_of_sampling_without_replacement():
    v = sp_sampling.vocabulary(sp_sampling.model_file(), 1.0)
    n, text = 6000, "the cat"
    part = sp_sampling.Slice(v, [text] * n, sp_sampling.row_keys(list(range(n)), 3))
    lat, probs = part.lat, {}

    def walk(w, node, path, lp):
        if lat.is_end[node]:
            if w == 1:
                probs[tuple(path)] = math.exp(lp)
                return
            w, node = w + 1, part.occ_root[w + 1]
        for e in range(lat.first[node], lat.first[node + 1]):
            walk(w, lat.end[e], [*path, int(lat.id[e])], lp + lat.log_q[e])

    walk(0, part.occ_root[0], [], 0.0)
    assert abs(sum(probs.values()) - 1) < 1e-9
    found, kappa = part.top(2)
    first = Counter(tuple(part.pieces(f[0][0]).tolist()) for f in found)
    second = Counter(tuple(part.pieces(f[1][0]).tolist()) for f in found)
    weight = Counter()
    for f, k in zip(found, kappa):
        for e, p, _ in f:
            weight[tuple(part.pieces(e).tolist())] += math.exp(p - sp_sampling.log_inclusion(p, k)) / n
    for key, p in sorted(probs.items(), key=lambda x: -x[1])[:3]:
        again = sum(q * p / (1 - q) for k, q in probs.items() if k != key)
        assert abs(first[key] / n - p) < 0.03 and abs(second[key] / n - again) < 0.03 and abs(weight[key] - p) < 0.03


# 9 near duplicates


def brute_simhash(rows):
    prints = []
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(ASCII_LOW))
        s = [" ".join(w[k : k + 3]) for k in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] if w else []
        h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
        prints.append((i, sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))))
    group = {f: {f} for _, f in prints}
    for a in list(group):
        for b in list(group):
            if bin(a ^ b).count("1") <= 2 and group[a] is not group[b]:
                merged = group[a] | group[b]
                for x in merged:
                    group[x] = merged
    least = {}
    for i, f in prints:
        if i is not None:
            for x in group[f]:
                least[x] = min(i, least.get(x, i))
    return sorted(((i, f"{f:016x}", least.get(f)) for i, f in prints), key=str)


def test_simhash(spark, docs, none):
    rows = [(x.doc_id, x.text) for x in docs.select("doc_id", "text").collect()] + [(i and i + 5000, t) for i, t in ODD]
    long = " ".join(f"w{k}" for k in range(400))
    rows += [(1000 + k, long.replace(f"w{7 * k} ", "zz ")) for k in range(12)]
    df = spark.createDataFrame([(*x, 1) for x in rows], DOCS + ", fp int")
    got = simhash.near_duplicates(df)
    assert sorted((tuple(x) for x in got.collect()), key=str) == brute_simhash(rows)
    ref = brute_simhash(rows)
    stay = sum(1 for i, _, c in ref if i is None or i == c)
    left = simhash.drop_near_duplicates(df)
    assert left.count() == stay and left.columns == df.columns
    assert simhash.near_duplicates(none).count() == 0


def test_links_against_all_pairs(spark):
    r = random.Random(9)
    base = [r.getrandbits(64) for _ in range(6)]
    prints = sorted({b ^ sum(1 << k for k in r.sample(range(64), r.randint(0, 3))) for b in base for _ in range(40)})
    signed = [p - (1 << 64) if p >> 63 else p for p in prints]
    df = spark.createDataFrame([(p,) for p in signed], "fp bigint")
    far = lambda a, b: bin((a ^ b) & (1 << 64) - 1).count("1")
    for distance, segments, full in ((2, 2, 256), (2, 2, 3), (3, 2, 5), (5, 4, 256), (2, 3, 4), (4, 2, 8)):
        want = sorted((min(a, b), max(a, b)) for n, a in enumerate(signed) for b in signed[n + 1 :] if far(a, b) <= distance)
        assert sorted(tuple(x) for x in simhash.links(df, distance, segments, full).collect()) == want, (distance, segments, full)


def test_components_of_a_long_chain(spark):
    df = spark.range(300).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert {x.component for x in connected_components(df).collect()} == {0}


# 10 toxicity


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        prev, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            prev, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, prev + (x != y))
    return row[-1]


def test_automata_find_what_edit_distance_finds():
    entries = [("idiot", False), ("worthless", False), ("disgusting", False), ("scum", False), ("lostra", True), ("achlich", True)]
    trie = toxicity.FuzzyTrie(entries)
    r = random.Random(1)
    for _ in range(3000):
        w = r.choice(entries)[0]
        for _ in range(r.randint(0, 3)):
            k, c = r.randint(0, len(w)), r.choice("abtosü")
            w = r.choice([w[:k] + c + w[k:], w[:k] + w[k + 1 :], w[:k] + c + w[k + 1 :]])
        want = []
        for n, (term, stem) in enumerate(entries):
            d = min(edits(term, w[:k]) for k in range(len(w) + 1)) if stem else edits(term, w)
            if d <= trie.edits(term, stem):
                want.append((d, n))
        got = trie.look(w)
        assert got == min(want, default=None) or got is not None and got[0] == min(want)[0], w


def test_toxicity_learns_and_holds_out(spark):
    r = random.Random(6)
    rows, labels = list(ODD), []
    for i in range(100, 900):
        words = [r.choice(["alpha", "beta", "gamma", "delta", "omega", "kappa"]) for _ in range(30)]
        bad = i % 7 == 0
        if bad:
            words[r.randint(0, 29)] = r.choice(["grumble", "grumbel", "snarkish"])
            words[r.randint(0, 29)] = "snarkish"
        rows.append((i, " ".join(words)))
        labels.append((i, int(bad)))
    labels += [(100, None), (None, 1), (99999, 1)]
    df = spark.createDataFrame([(*x, 1) for x in rows], DOCS + ", __tox int")
    lab = spark.createDataFrame(labels, "doc_id bigint, toxic int")
    model = toxicity.train_model(df, lab)
    assert any(t == "snarkish" for t, _, _ in model.entries)
    got = toxicity.score(df, model)
    assert got.count() == len(rows)
    truth = dict(x for x in labels if x[0] is not None)
    for x in got.collect():
        assert 0 <= x.score <= 1 and x.predicted == (x.score >= 0.3) and x.held_out == (x.doc_id is not None and __import__("zlib").crc32(str(x.doc_id).encode()) % 4 == 2)
        if x.doc_id in truth:
            assert x.predicted == (truth[x.doc_id] or 0)
    assert toxicity.drop_toxic(df, model).count() == len(rows) - got.where("predicted = 1").count()
    empty = toxicity.train_model(df, lab.where("false"))
    assert {x.score for x in toxicity.score(df, empty).collect()} == {0.0}


def test_quotation_context():
    s = 'he said "you idiot" twice\nyou idiot\n> idiot line\n"' + "x " * 500 + 'idiot" idiot' + "\nno idiot" + ' "idiot'
    assert toxicity.quoted(s, [m.span() for m in re.finditer("idiot", s)]) == [True, False, True, True, False, False, False]


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    got = registry.op10_toxicity(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out")
    tp, fp, fn = (got.where(c).count() for c in ("predicted = 1 and toxic = 1", "predicted = 1 and toxic = 0", "predicted = 0 and toxic = 1"))
    assert tp / (tp + fp) > 0.85 and tp / (tp + fn) > 0.85
