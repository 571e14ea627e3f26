"""Context of a run over its whole interval, against plain loops."""

import datetime
import random

from pyspark.sql import functions as F

from slowlens.operators import enrich, targets

T0 = datetime.datetime(2024, 1, 1)
LEVELS = ("Info", "Alarm", "Critical", "Blocking")


def at(us):
    return T0 + datetime.timedelta(microseconds=us)


def made(spark, seed):
    """Runs of up to a minute, spans from none to days long, over a midnight."""
    rng = random.Random(seed)
    near = 86_400_000_000
    runs = [(i, rng.randrange(2), near + rng.randrange(-60_000_000, 60_000_000), rng.choice([1, 9_999_999, 10_000_000, rng.randrange(1, 60_000_000)])) for i in range(60)]
    spans = [(rng.randrange(2), rng.choice("xy"), rng.choice(LEVELS), b := near + rng.randrange(-90_000_000, 90_000_000), b + rng.choice([0, 5_000_000, 30_000_000, 3 * near])) for _ in range(40)]
    log = spark.createDataFrame([(o, s, at(b), at(b + n)) for o, s, b, n in runs], "oid long, server int, started timestamp, ended timestamp")
    held = spark.createDataFrame([(s, k, v, at(a), at(b)) for s, k, v, a, b in spans], "server int, kind string, level string, from_ts timestamp, to_ts timestamp")
    return [(o, s, b, b + n) for o, s, b, n in runs], spans, log, held


def test_waits_and_alerts_over_the_run(spark):
    runs, spans, log, held = made(spark, 1)
    shared = {o: [(k, v) for t, k, v, f, u in spans if t == s and f < u and f < e and u > b] for o, s, b, e in runs}
    waits = {r["oid"]: (r["w_x"], r["w_y"]) for r in enrich.with_waits(log, held, ["x", "y"]).collect()}
    assert waits == {o: tuple(sum(k == c for k, _ in p) for c in "xy") for o, p in shared.items()}
    alerts = {r["oid"]: r["a_x"] for r in enrich.with_alerts(log, held, ["x"], LEVELS).collect()}
    assert alerts == {o: max((v for k, v in p if k == "x"), key=LEVELS.index, default=None) for o, p in shared.items()}


def test_concurrence_is_the_best_ten_seconds(spark):
    step = 10_000_000
    seen = set()
    for seed, level in ((2, 1), (3, 2), (4, 3)):
        runs, spans, log, held = made(spark, seed)
        want = {}
        for o, s, b, e in runs:
            periods = [(a, min(a + step, e)) for a in range(b, e, step)]
            best = max(sum(max(0, min(z, u) - max(a, f)) for t, _, _, f, u in spans if t == s) / (z - a) for a, z in periods)
            want[o] = int(best >= level - 1e-12)
        got = {r["oid"]: r["concurrence"] for r in targets.concurrence(log, held, level).collect()}
        assert got == want
        seen |= set(want.values())
    assert seen == {0, 1}


def test_end_of_a_run(spark):
    df = spark.sql("SELECT TIMESTAMP'2024-01-01' AS a, CAST(x AS DECIMAL(9,2)) AS s FROM VALUES (0), (NULL), (1.25) v(x)")
    ends = [r[0] for r in df.select(F.unix_micros(enrich.run_end(F.col("a"), F.col("s"))) - F.unix_micros("a")).collect()]
    assert ends == [1, 1, 1_250_000]
