from pyspark.sql import functions as F

from ebbset.functions.hashing import level_of, shift_hash
from ebbset.operators import baselines, candidates, l0, similarity, sketch, updates
from ebbset.params import ANDERBERG, DICE, HAMMING, JACCARD, ROGERS_TANIMOTO, SketchParams
from ebbset.streaming import maintain

# The golden trace's hash constants.
LEVEL, BUCKET = (2654435769, 12345), (2246822519, 54321)


class Golden(SketchParams):
    def draw(self, purpose, count):
        return {"level": [LEVEL], "bucket": [BUCKET]}.get(purpose) or super().draw(purpose, count)


GOLDEN = Golden(log_m=4, buckets=8)
TRACE = [("A", 1, 1), ("A", 2, 1), ("A", 3, 1), ("A", 5, 1), ("A", 8, 1), ("A", 13, 1), ("B", 2, 1), ("B", 3, 1), ("B", 5, 1), ("B", 8, 1), ("B", 11, 1), ("A", 3, -1), ("B", 11, -1), ("B", 1, 1)]


def stream(spark, rows):
    return spark.createDataFrame([(s, i, d, k) for k, (s, i, d) in enumerate(rows)], "set_id string, item_id long, delta int, seq long")


def numbered(spark, rows):
    return spark.createDataFrame([(s, i, d, k) for k, (s, i, d) in enumerate(rows)], "set_id long, item_id long, delta int, seq long").withColumn("ts", F.lit(None).cast("timestamp_ntz"))


def test_golden_trace(spark):
    items = spark.createDataFrame([(i,) for i in (1, 2, 3, 5, 8, 11, 13)], "i long")
    h = shift_hash(F.col("i"), LEVEL, 4)
    rows = items.select("i", h, level_of(h, 4), shift_hash(F.col("i"), BUCKET, 3)).collect()
    assert [tuple(r) for r in rows] == [(1, 9, 1, 4), (2, 3, 1, 0), (3, 13, 1, 4), (5, 1, 1, 4), (8, 15, 1, 1), (11, 12, 3, 6), (13, 0, 4, 6)]
    got = {tuple(r) for r in sketch.cells(stream(spark, TRACE), GOLDEN, mode="raw").collect()}
    a = {("A", 0, 0, 1), ("A", 0, 1, 1), ("A", 0, 4, 2), ("A", 0, 6, 1), ("A", 1, 0, 1), ("A", 1, 1, 1), ("A", 1, 4, 2), ("A", 4, 6, 1)}
    b = {("B", 0, 0, 1), ("B", 0, 1, 1), ("B", 0, 4, 3), ("B", 1, 0, 1), ("B", 1, 1, 1), ("B", 1, 4, 3)}
    assert got == a | b


def test_levels(spark):
    h = spark.createDataFrame([(x,) for x in (1, 2, 8, 12, 0)], "h long")
    assert [r[0] for r in h.select(level_of(F.col("h"), 10)).collect()] == [1, 2, 4, 3, 10]


def test_pair_of_ten(spark):
    inter, union, symdiff, u = (F.lit(v) for v in (2, 5, 3, 10))
    row = spark.range(1).select(*[similarity.rational_similarity(inter, union, symdiff, u, s) for s in (JACCARD, HAMMING, ANDERBERG, ROGERS_TANIMOTO, DICE)]).first()
    assert [round(x, 12) for x in row] == [round(x, 12) for x in (2 / 5, 7 / 10, 2 / 8, 7 / 13, 4 / 7)]
    empty = spark.range(1).select(similarity.rational_similarity(F.lit(0), F.lit(0), F.lit(0), F.lit(0), JACCARD)).first()
    assert empty[0] == 1.0


def test_set_semantics(spark):
    rows = numbered(spark, [(1, 7, 1), (1, 7, -1), (1, 7, 1), (2, 7, 1), (2, 7, 1), (2, 7, -1), (3, 7, -1), (3, 7, 1), (4, 7, -1)])
    assert {tuple(r) for r in updates.net_sets(rows).collect()} == {(1, 7), (2, 7)}
    assert [tuple(r) for r in updates.audit(rows).collect()] == [(4, 7, -1)]


def test_eager_lazy_and_batch_agree(spark):
    p = SketchParams(log_m=8, buckets=64, alpha=0.2, r1=0.5, rows=2, bands=3)
    rows = [(s, (s * 31 + k * 17) % 90, 1) for s in (1, 2) for k in range(60)]
    rows = list(dict.fromkeys(rows))
    rows += [(s, i, -1) for s, i, _ in rows if i % 3 == 0]
    u = numbered(spark, rows)
    cards = updates.cardinalities(updates.net_sets(u))
    held = candidates.occupied(sketch.cells(u, p), candidates.level_windows(cards, p))
    want = {(r.set_id, r.level): list(r.sig) for r in candidates.signatures(held, p).collect()}
    assert want == {(r.set_id, r.level): list(r.sig) for r in candidates.signatures_fast(held, p).collect()}
    for selective in (True, False):
        got = maintain.eager_signatures(u, p, selective).collect()
        assert want == {(r.set_id, r.level): list(r.sig) for r in got}
    lazy = {r.set_id: r.rebuilt for r in maintain.eager_signatures(u, p, True).collect()}
    eager = {r.set_id: r.rebuilt for r in maintain.eager_signatures(u, p, False).collect()}
    assert all(lazy[s] <= eager[s] for s in eager)


def test_streams_give_the_batch_cells(spark, tmp_path):
    p = SketchParams(log_m=8, buckets=64)
    rows = [(s, i, 1) for s in (1, 2, 3) for i in range(40)] + [(1, i, -1) for i in range(40)]
    u = numbered(spark, rows).drop("ts")
    u.repartition(3).write.parquet(str(tmp_path / "in"))
    live = maintain.drained(maintain.stream_cells(maintain.read_updates(spark, str(tmp_path / "in")), p), "live_cells", "complete")
    assert {tuple(r) for r in live.where("cnt <> 0").collect()} == {tuple(r) for r in sketch.cells(u, p).select("set_id", "level", "bucket", "cnt").collect()}


def test_linear_distinct_counts(spark):
    p = SketchParams(log_m=12, buckets=1024)
    rows = [(1, i, 1) for i in range(1000)] + [(2, i, 1) for i in range(500, 1500)] + [(2, i, 1) for i in range(5000, 5400)] + [(2, i, -1) for i in range(5000, 5400)]
    u = numbered(spark, rows)
    sk = l0.l0_cells(u, p, 3)
    pairs = spark.createDataFrame([(1, 2)], "left_id long, right_id long")
    z = l0.sizes(pairs, sk, p).first()
    assert abs(z.uni - 1500) < 150 and abs(z.symdiff - 1000) < 120
    d = l0.sketched_distance(pairs, sk, 10000, JACCARD, p).first().distance
    assert abs(d - 2 / 3) < 0.08
    same = l0.sizes(spark.createDataFrame([(1, 1)], "left_id long, right_id long"), sk, p).first()
    assert same.symdiff == 0


def test_stale_minhash_drifts(spark):
    p = SketchParams(rows=2, bands=4)
    u = numbered(spark, [(1, i, 1) for i in range(50)] + [(1, i, -1) for i in range(45)])
    assert baselines.drift(u, updates.net_sets(u), p).first().wrong > 0
    assert baselines.rescan_cost(u).first().removals == 45
