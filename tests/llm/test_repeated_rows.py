import numpy as np

from ebbset.llm import mtree, queries


def test_repeated_rows_count_once(spark):
    import duckdb

    r = np.random.default_rng(6)
    base = [(i, [float(x) for x in r.integers(-4, 5, 3)]) for i in range(1, 120)]
    rows = [(0, [1.0, 1.0, 1.0]), *base] + [(i, [float(x) for x in r.integers(3, 5, 3)]) for i in (7, 8)] * 9 + [(9, [4.0, 4.0, y]) for y in (1.0, 2.0, 3.0) for _ in range(6)] + [(50, [1.0, 1.0, 0.0]), (100, [1.0, 0.0, 0.0])] * 3
    got = sorted(map(tuple, mtree.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()))
    con = duckdb.connect()
    con.sql("CREATE TABLE embeddings (vec_id BIGINT, embedding FLOAT[])")
    con.executemany("INSERT INTO embeddings VALUES (?, ?)", rows)
    assert got == sorted(con.sql(queries.ORACLE["op8_mtree_top_k"]).fetchall())


def test_regions_pass_limits_on(spark, monkeypatch):
    """Several regions, parts and blocks give what one scan gives, and far regions are left out."""
    monkeypatch.setattr(mtree, "PART_ROWS", 60)
    monkeypatch.setattr(mtree, "BLOCK_QUERIES", 8)
    monkeypatch.setattr(mtree, "MOST_REGIONS", 6)
    r = np.random.default_rng(11)
    center = r.normal(size=(5, 4)) * 3
    x = center[r.integers(0, 5, 900)] + r.normal(size=(900, 4)) * 0.2
    rows = [(i, [float(v) for v in x[i].astype(np.float32)]) for i in range(900)] + [(50, [0.0] * 4)]
    got = sorted(map(tuple, mtree.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()))
    own = [(i, np.floor(np.array(v) * 256).astype(np.int64)) for i, v in rows]
    want = []
    for i in range(0, 900, 50):
        score = {(-int(v @ w), j) for k, v in own if k == i for j, w in own if j != i}
        want += [(i, n + 1, j, -s) for n, (s, j) in enumerate(sorted(score)[:5])]
    assert got == want
