"""The pipeline's near-copy stage against all pairs of five-word shingle sets."""

import random
import re

import corpus_pipeline
from tests.llm.test_operators import ASCII_LOW, ODD

SF = "/root/testdata/sf0.001"


def brute_similar(rows, size=5):
    """The smallest id of the component of each row."""
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(ASCII_LOW))
        sets.setdefault(frozenset(tuple(w[k : k + size]) for k in range(max(len(w) - size + 1, min(len(w), 1)))), []).append(i)
    group = {s: {s} for s in sets}
    for a in list(group):
        for b in list(group):
            if group[a] is not group[b] and 5 * len(a & b) >= 4 * len(a | b):
                merged = group[a] | group[b]
                for x in merged:
                    group[x] = merged
    return {i: min((j for x in group[s] for j in sets[x] if j is not None), default=None) for s, ids in sets.items() for i in ids}


def test_near_stage(spark):
    r = random.Random(8)
    rows = [(x.doc_id, x.text) for x in spark.read.parquet(f"{SF}/documents.parquet").collect()] + [(i and i + 5000, t) for i, t in ODD]
    for base in range(4):
        words = [f"w{base}x{k}" for k in range(150)]
        for k in range(30):  # similarities on both sides of 0.8, and chains of them
            at = r.sample(range(150), r.randint(0, 7))
            rows.append((6000 + 100 * base + k, " ".join("zz" if j in at else w for j, w in enumerate(words))))
    df = spark.createDataFrame([(*x, 1) for x in rows], "doc_id bigint, text string, n int")
    want = brute_similar(rows)
    got = corpus_pipeline.near_stage(spark, df, SF)
    assert got.columns == df.columns
    assert sorted(x.doc_id for x in got.collect() if x.doc_id is not None) == sorted(i for i, _ in rows if i is not None and want[i] == i)
    assert want[6001] == 6000 and 145 in want and want[145] == 6  # seven bits apart as three-word fingerprints
    assert corpus_pipeline.near_stage(spark, df.where("false"), SF).count() == 0


def test_near_fingerprints_are_candidates(spark):
    from rpqframe.llm import shingle_dedup as S
    from rpqframe.llm.simhash import fingerprint

    r = random.Random(9)
    words = [f"w{k}" for k in range(400)]
    texts = [" ".join(words + [f"end{k}"] * (k % 3)) for k in range(6)] + [" ".join(r.choices(words, k=50)) for _ in range(20)] + [None, "one two"]
    df = spark.createDataFrame(list(enumerate(texts)), "id bigint, text string").coalesce(1)
    rows = S.prints(df, S.SIZE, S.common_shingles(df)).cache()
    got = {(x.a, x.b) for x in S._Links(df, rows, S.SIZE).near_prints().collect()}
    sig, fp = {x.id: x.sig for x in rows.collect()}, {x.id: x.fp & (1 << 64) - 1 for x in rows.collect()}
    assert all(fp[i] == fingerprint(t and t.encode(), S.SIZE) for i, t in enumerate(texts))
    near = {tuple(sorted((sig[i], sig[j]))) for i in fp for j in fp if sig[i] != sig[j] and (fp[i] ^ fp[j]).bit_count() <= S.DISTANCE}
    assert near and got <= near and all(any(set(p) & set(q) for q in got) for p in near)
