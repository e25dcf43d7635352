"""Cases that a review found wrong or too large."""

import datetime

import pytest

from ebbset.plans import extended, relational, workloads
from ebbset.streaming import maintain

QUERIES, ORACLE = workloads.QUERIES | relational.QUERIES | extended.QUERIES, workloads.ORACLE | relational.ORACLE | extended.ORACLE


def same_as_sql(spark, name, folder, **tables):
    """Writes the tables (Arrow) and compares a query with its SQL on them."""
    import duckdb
    import pyarrow.parquet as pq

    con = duckdb.connect()
    for table, rows in tables.items():
        pq.write_table(rows, f"{folder}/{table}.parquet")
        con.sql(f"CREATE VIEW {table} AS SELECT * FROM '{folder}/{table}.parquet'")
    df, want = QUERIES[name](spark, str(folder)), con.sql(ORACLE[name])
    cols = sorted(df.columns)
    assert cols == sorted(want.columns)
    got = sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)
    at = [want.columns.index(c) for c in cols]
    assert got == sorted((tuple(r[i] for i in at) for r in want.fetchall()), key=repr)
    return got


def events(rows):
    """rows: (user, topic, time)."""
    import pyarrow as pa

    user, topic, ts = zip(*rows, strict=True)
    kinds = ["view", "purchase", "error"]
    return pa.table({
        "event_id": pa.array(range(len(rows)), pa.int64()), "ts": pa.array(ts, pa.timestamp("us")), "user_id": pa.array(user, pa.int64()),
        "event_type": [kinds[i % 3] for i in range(len(rows))], "value": [1.0] * len(rows), "props": [f'{{"k": {t}}}' for t in topic],
    })


def test_seconds_are_rounded_as_in_the_sql(spark, tmp_path):
    at = datetime.datetime(2024, 1, 1)
    ms = lambda x: datetime.timedelta(milliseconds=x)
    week = 604_800_000
    same_as_sql(spark, "win_range_7d", tmp_path, events=events([(1, 1, at + ms(400)), (1, 1, at + ms(600)), (1, 1, at + ms(week + 500)), (1, 1, at + ms(week + 1500)), (1, 1, at + ms(week + 700))]))


@pytest.mark.parametrize("name", ["stream_sketch_cells", "stream_static_join"])
def test_streams_leave_no_table_on_the_driver(spark, monkeypatch, name):
    def refused(*_):
        raise AssertionError("rows kept on the driver")

    monkeypatch.setattr(maintain, "drained", refused)
    assert QUERIES[name](spark, "/root/testdata/sf0.001").count() > 0


def copies(n=30):
    """Users with few different sets of topics."""
    at = datetime.datetime(2024, 1, 28)
    topics = [(1, 2, 3), (2, 3, 4), (1, 2, 3, 4, 5), (9,)]
    return events([(u, t, at + datetime.timedelta(minutes=k)) for u in range(n) for t in topics[u % 4] for k in range(2)])


@pytest.mark.parametrize("name", ["exact_jaccard_pairs", "exact_hamming_pairs", "exact_anderberg_pairs", "exact_rogers_tanimoto_pairs", "exact_dice_pairs", "exact_root_pairs", "denominator_forms"])
def test_equal_sets_are_one_class(spark, tmp_path, name):
    got = same_as_sql(spark, name, tmp_path, events=copies())
    assert len(got) == 3 + 26  # three pairs of the four classes share a topic, all other sets belong to one


def test_distances_are_by_class(spark, tmp_path):
    assert len(same_as_sql(spark, "distance_presets", tmp_path, events=copies())) == 6 * 29


def test_sizes_are_named_by_their_smallest_set(spark, tmp_path):
    assert len(same_as_sql(spark, "size_candidates", tmp_path, events=copies())) == 27 + 1  # sizes 3, 5 and 1


def test_curve_weighs_classes(spark, tmp_path):
    same_as_sql(spark, "sensitivity_curve", tmp_path, events=copies())
    found, exact = workloads.by_class(*[workloads.STREAMS["events_expiry"][0], workloads.SMALL])(spark, str(tmp_path))
    assert exact.count() == 3 + 4 and exact.agg({"weight": "sum"}).first()[0] == 8 * 8 + 8 * 7 * 2 + 2 * 28 + 2 * 21


def test_samples_are_counted_in_one_pass(spark):
    plan = QUERIES["sampling_lemma"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan


@pytest.mark.parametrize("name", ["calculators", "detect_curve", "metric_flags", "synthetic_rows", "synthetic_stream", "synthetic_bands", "synthetic_recall"])
def test_reads_a_given_table(spark, name):
    df = QUERIES[name](spark, "/root/testdata/sf0.001")
    assert df.inputFiles() and df.count() > 0


def test_blocks_lose_no_pair(spark, monkeypatch):
    from ebbset.operators import blocks

    rows = [(s, (s * k) % 37) for s in range(60) for k in range(1 + s % 7)]
    sets = {}
    for s, i in rows:
        sets.setdefault(s, set()).add(i)
    want = {(a, b, len(sets[a] & sets[b]), len(sets[a] | sets[b])) for a in sets for b in sets if a < b and sets[a] & sets[b]}
    view = spark.createDataFrame(rows, "set_id long, item_id long").distinct()
    monkeypatch.setattr(blocks, "SETS", 7)
    assert {tuple(r) for r in blocks.exact_pairs(view).collect()} == want


def test_more_sets_than_a_bound_meet_each_other(spark):
    from ebbset.operators import candidates, sketch, updates
    from ebbset.params import SketchParams

    p = SketchParams(log_m=4, buckets=64)
    cards = spark.range(5001).selectExpr("id AS set_id", "1 AS card")
    none = sketch.packed(sketch.cells(updates.insert_stream(spark.createDataFrame([(0, 1)], "set_id long, item_id long")), p), p)
    assert candidates.estimate_all(none, cards, p).count() == 5001 * 5000 // 2


def test_similar_pairs_are_all_found(spark):
    import random

    from ebbset.operators import similarity

    r = random.Random(5)
    sets = {s: {min(r.randrange(60), r.randrange(60)) for _ in range(r.randrange(1, 25))} for s in range(120)}
    view = spark.createDataFrame([(s, i) for s, own in sets.items() for i in own], "set_id long, item_id long")
    for low in (0.2, 0.353553391, 0.5, 1.0):
        want = {(a, b, len(sets[a] & sets[b]), len(sets[a] | sets[b])) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= low * len(sets[a] | sets[b])}
        assert {tuple(x) for x in similarity.similar_pairs(view, low).collect()} == want


@pytest.mark.parametrize("name", ["band_tuning", "near_duplicate_groups", "squared_deviation_docs", "confusion_docs_production", "strict_recall_docs"])
def test_documents_need_not_all_meet(spark, monkeypatch, name):
    def refused(*_):
        raise AssertionError("every pair of documents that share a shingle")

    monkeypatch.setattr(workloads.similarity, "exact_pairs", refused)
    assert QUERIES[name](spark, "/root/testdata/sf0.001").count() > 0


def test_an_empty_block_repeats_no_pair(spark):
    from ebbset.operators import blocks

    for many in range(1, 13):
        view = spark.createDataFrame([(s, 1) for s in range(many)], "set_id long, item_id long")
        assert blocks.exact_pairs(view).count() == many * (many - 1) // 2


@pytest.mark.parametrize("name", ["eager_equals_lazy", "online_minhash"])
def test_a_set_that_lost_all_its_items_has_no_signature(spark, tmp_path, name):
    day = lambda d: datetime.datetime(2024, 1, 1) + datetime.timedelta(days=d)
    assert len(same_as_sql(spark, name, tmp_path, events=events([(1, 5, day(0)), (1, 5, day(1)), (2, 6, day(25)), (2, 6, day(26))]))) == 1


def test_a_null_item_is_in_no_bucket(spark, tmp_path):
    day = lambda d: datetime.datetime(2024, 1, 1) + datetime.timedelta(days=d)
    rows = [(u, t, day(25 + k)) for u, t in ((1, "null"), (1, 7), (2, 8), (None, 9)) for k in range(2)]
    assert len(same_as_sql(spark, "eager_equals_lazy", tmp_path, events=events(rows))) == 2


def test_dense_sets_meet_by_products(spark, monkeypatch):
    import numpy as np

    from ebbset.operators import blocks

    r = np.random.default_rng(3)
    for many, universe in ((40, 12), (40, 4000)):
        sets = [np.unique(r.integers(0, universe, r.integers(1, 12))) for _ in range(many)]
        flat, at = np.concatenate(sets), np.concatenate([[0], np.cumsum([len(x) for x in sets])])
        want = [[len(np.intersect1d(x, y)) for y in sets] for x in sets]
        if universe == 12:
            monkeypatch.setattr(blocks, "strips", None)  # not needed
        else:
            monkeypatch.undo()
        monkeypatch.setattr(blocks, "CELLS", 100)
        assert np.concatenate([c.reshape(hi - lo, many) for lo, hi, c in blocks.counts(flat, at, flat, at)]).tolist() == want


def test_sizes_of_met_pairs_are_those_of_joined_cells(spark, monkeypatch):
    import random

    from ebbset.operators import blocks, l0, similarity, updates
    from ebbset.params import SketchParams

    monkeypatch.setattr(blocks, "SETS", 9)
    r = random.Random(4)
    rows = [(s, i, 1) for s in range(40) for i in {r.randrange(300) for _ in range(1 + 5 * s)}] + [(s, 1, -1) for s in range(0, 40, 5)]
    stream = spark.createDataFrame(rows, "set_id long, item_id long, delta int")
    net = updates.net_sets(stream)
    for p in (SketchParams(log_m=12, buckets=64), SketchParams(log_m=2, buckets=64)):
        cells = l0.l0_cells(stream, p, 3)
        pairs = similarity.exact_pairs(net)
        want = {(x.left_id, x.right_id): (round(x.uni, 6), round(x.symdiff, 6)) for x in l0.sizes(pairs, cells, p).collect()}
        got = l0.exact_and_estimated(net, cells, p, 3)
        assert {(x.left_id, x.right_id): (round(x.uni_est, 6), round(x.symdiff_est, 6)) for x in got.collect()} == want and len(want) > 600
        assert {tuple(x) for x in got.select("left_id", "right_id", "inter", "uni").collect()} == {tuple(x) for x in pairs.collect()}


def test_estimates_of_all_suppliers_join_no_cells(spark):
    plan = QUERIES["l0_distance_estimates"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan


def test_draws_plant_at_the_given_chances(spark):
    from ebbset.operators import updates
    from ebbset.params import flip_rates

    view = spark.createDataFrame([(s, 0 if i == 7 else i) for s in range(1, 41) for i in range(1, 4001, 3)], "set_id long, item_id long")
    out = updates.planted_by_draws(view, 5, 0.5, 0.25, 4000)
    rows = [tuple(r) for r in out.collect()]
    assert len(rows) == len(set(rows)) and set(rows) >= {tuple(r) for r in view.collect()}
    assert sorted(rows) == sorted(tuple(r) for r in out.collect())
    own, (drop, add) = {0, *range(1, 4001, 3)} - {7}, flip_rates(0.5, 0.25)
    new = [i for s, i in rows if s > 10_000_000 and i not in own]
    assert {s for s, _ in rows if s > 10_000_000} == {10_000_000 + s for s in range(5, 41, 5)}
    assert min(new) >= 1 and max(new) <= 4000 and len(set(new)) > 1500
    assert abs(len(new) - 8 * 2667 * add) < 5 * (8 * 2667 * add) ** 0.5
    assert abs(sum(s > 10_000_000 and i in own for s, i in rows) - 8 * 1334 * (1 - drop)) < 5 * (8 * 1334 * drop) ** 0.5


def test_no_dice_for_each_id_that_a_set_lacks(spark):
    plan = QUERIES["planted_pairs_whole"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "explode" not in plan.lower() and "Join" not in plan


def test_samples_that_fit_are_not_looked_at_by_level(monkeypatch):
    """Pairs of sets whose densest samples fit, met block against itself: no nesting of levels for any of them."""
    import numpy as np
    import pyarrow as pa

    from ebbset.operators import l0
    from ebbset.params import SketchParams

    p, r, sets = SketchParams(log_m=12, buckets=1024), np.random.default_rng(6), 30
    monkeypatch.setattr(l0, "_items", None)  # not needed
    items = [np.unique(r.integers(0, 300, 60)) for _ in range(sets)]
    cell = r.integers(1, 1 << 30, (3, 300)) | r.integers(0, 12 * 1024, (3, 300)) << 31
    keys = [np.concatenate([cell[k, x] + (k * 12 * 1024 << 31) for k in range(3)]) for x in items]
    keys = [k[np.unique(k >> 31, return_index=True)[1]] for k in keys]
    lists = [pa.array([x.tolist() for x in c], pa.list_(pa.int64())) for c in (items, keys)]
    cols = [pa.array(range(sets)), lists[0], pa.array([len(x) for x in items]), lists[1], pa.array([0] * sets), pa.array([False] * sets)]
    batch = pa.RecordBatch.from_arrays(cols, ["set_id", "items", "card", "keys", "pair", "second"])
    rows = pa.Table.from_batches(l0._met([batch], p, 3, 1)).to_pylist()
    assert len(rows) == sets * (sets - 1) // 2
    assert all(abs(x["uni_est"] - x["uni"]) < 0.25 * x["uni"] and abs(x["symdiff_est"] - x["uni"] + x["inter"]) < 0.25 * x["uni"] for x in rows)


@pytest.mark.parametrize("name", ["confusion_docs_production", "accuracy_recall_docs_thinned", "confusion_docs_thinned"])
def test_sets_are_counted_without_another_pass(spark, monkeypatch, name):
    from ebbset.operators import updates

    calls, own = [], updates.net_sets
    monkeypatch.setattr(updates, "net_sets", lambda u: calls.append(1) or own(u))
    QUERIES[name](spark, "/root/testdata/sf0.001")
    assert len(calls) == 1
