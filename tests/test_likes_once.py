"""likes orders the days once: purchases with and without a view on their own day come from one pass."""

from pyspark.sql import functions as F

from rpqframe.sources.tables import Tables, likes

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def plain(rows):
    """The latest strictly earlier view of another user for each user's first purchase."""
    rows = sorted(rows, key=lambda r: (r[1], r[0]))
    out, bought = set(), set()
    for k, (event, _, user, kind) in enumerate(rows):
        if kind == "purchase" and user not in bought:
            bought.add(user)
            seen = [r for r in rows[:k] if r[3] == "view" and r[2] != user]
            if seen:
                out.add((event, user, seen[-1][0]))
    return out


def test_likes_is_one_pass(spark, tmp_path):
    spans = [(d, h) for d in (1, 2, 4, 5, 9) for h in (3, 3, 10, 20)]
    kinds = ["view", "purchase", "view", "click", "purchase", "purchase", "purchase"]
    rows = [(i, f"2024-03-{d:02d} {h:02d}:00:00", (i * i + i // 5) % 6, kinds[i % 7]) for i, (d, h) in enumerate(spans)]
    rows += [(99, "2024-03-01 01:00:00", 7, "purchase"), (98, "2024-03-12 01:00:00", 8, "purchase"), (97, "2024-03-14 01:00:00", 9, "purchase")]
    df = spark.createDataFrame(rows, "event_id bigint, at string, user_id bigint, event_type string")
    df.select("event_id", F.col("at").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", F.lit(0.0).alias("value"), F.lit("{}").alias("props")).write.parquet(str(tmp_path / "events.parquet"))
    found = likes(Tables(spark, str(tmp_path)))
    kind = 10**15
    want = plain(rows)
    assert {(r.eid - 22 * kind, r.src - kind, r.dst - 2 * kind) for r in found.collect()} == want and len(want) > 4
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Union") == 1
