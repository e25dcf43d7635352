"""More registered queries: variants of the filter, linear sketches, theory checks, the synthetic benchmark, streams.

Same rules as in workloads: hash constants go into both sides, so randomised structures compare value for value.
"""

from __future__ import annotations

import uuid
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ebbset import params as P
from ebbset.functions.hashing import field_hash, hash_input, level_of, shift_hash
from ebbset.operators import applications, baselines, blocks, candidates, evaluate, l0, similarity, sketch, synthetic, updates
from ebbset.plans import workloads as W
from ebbset.sources import views
from ebbset.streaming import maintain

QUERIES: dict[str, W.Query] = {}
ORACLE: dict[str, str] = {}
SMALL = W.SMALL


def add(name: str, query: W.Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLE[name] = sql


LIVE, LIVE_SQL = W.STREAMS["events_expiry"]
SUP, SUP_SQL = W.STREAMS["suppliers_thinned"]
TOPICS, TOPICS_SQL = W.STREAMS["topics_thinned"]

# --- variants of the filter -----------------------------------------------------------------------------------------------

UNAMPLIFIED = P.SketchParams(log_m=12, buckets=128, alpha=0.1, r1=0.5, rows=1, bands=1)
add("candidates_unamplified", W.found(LIVE, UNAMPLIFIED), W.candidates_sql(LIVE_SQL, UNAMPLIFIED))


def anderberg_params(r: float) -> P.SketchParams:
    """Jaccard settings that find all pairs of that Anderberg similarity, which grows with Jaccard's."""
    return P.SketchParams(log_m=12, buckets=128, alpha=0.1, r1=2 * r / (1 + r), rows=2, bands=4)


ANDERBERG = anderberg_params(1 / 3)
add("anderberg_candidates", W.found(LIVE, ANDERBERG), W.candidates_sql(LIVE_SQL, ANDERBERG))
add("candidates_sorted", lambda s, d: candidates.sorted_candidates(W.banded(SUP, SMALL)(s, d), SMALL.r1), W.candidates_sql(SUP_SQL, SMALL))


def _bipartite(s, d):
    own = W.banded(SUP, SMALL)(s, d)
    return candidates.between(own.where("set_id % 10 <> 0"), own.where("set_id % 10 = 0"), SMALL.r1)


add(
    "bipartite_query",
    _bipartite,
    f"""WITH c AS ({W.candidates_sql(SUP_SQL, SMALL)}), b AS (SELECT left_id AS query_id, right_id AS set_id FROM c UNION ALL SELECT right_id, left_id FROM c)
        SELECT query_id, set_id FROM b WHERE query_id % 10 = 0 AND set_id % 10 <> 0""",
)


def _classes(s, d):
    _, cards, c = W.parts(LIVE, SMALL)(s, d)
    return candidates.signature_classes(candidates.signatures_fast(candidates.occupied(c, candidates.level_windows(cards, SMALL)), SMALL))


add(
    "signature_classes",
    _classes,
    f"""WITH k AS (SELECT set_id, string_agg(level || ':' || band || ':' || band_key, ',' ORDER BY level, band) AS name FROM ({W.bands_sql(LIVE_SQL, SMALL)}) GROUP BY 1)
        SELECT set_id, min(set_id) OVER (PARTITION BY name) AS rep FROM k""",
)
LEVEL = 2


def _fixed(s, d):
    """Candidates at one level for all sets, whatever their sizes: the route for Hamming and Rogers-Tanimoto."""
    _, cards, c = W.parts(SUP, SMALL)(s, d)
    held = candidates.occupied(c, candidates.fixed_level(cards, LEVEL))
    return candidates.candidates(candidates.hashed_bands(candidates.signatures_fast(held, SMALL), SMALL), 0.0)


_fixed_sql = W.candidates_sql(SUP_SQL, SMALL).replace(
    W.windows_sql(W.cards_sql(W.net_sql(SUP_SQL)), SMALL), f"SELECT set_id, card, {LEVEL} AS level FROM ({W.cards_sql(W.net_sql(SUP_SQL))})"
).replace(f"l.card >= {SMALL.r1} * r.card AND r.card >= {SMALL.r1} * l.card", "true")
add("fixed_level_candidates", _fixed, _fixed_sql)
add("refined_by_estimate", lambda s, d: W.estimated(SUP, SMALL)(s, d).where("est >= 0.2").select("left_id", "right_id"), f'SELECT left_id, right_id FROM ({W.estimates_sql(SUP_SQL, SMALL)}) WHERE "both" >= 0.2 * either')


def _rational(s, d):
    """Hamming and Rogers-Tanimoto from the samples at one level; the sampled universe is the number of buckets."""
    e = W.estimated(SUP, SMALL)(s, d)
    one = lambda m: candidates.estimate_rational(e, SMALL.buckets, m).select("left_id", "right_id", F.lit(m.name).alias("name"), F.round("est", 6).alias("est"))
    return one(P.HAMMING).union(one(P.ROGERS_TANIMOTO)).union(one(P.DICE))


def _rational_sql(m: P.Similarity) -> str:
    base, apart = f'({m.x} * "both" + {m.y} * ({SMALL.buckets} - either))', '(either - "both")'
    return f"""SELECT left_id, right_id, '{m.name}' AS name, CASE WHEN {base} + {m.zp} * {apart} = 0 THEN 1.0 ELSE
        round(({base} + {m.z} * {apart})::DOUBLE / ({base} + {m.zp} * {apart}), 6) END AS est FROM e"""


add("estimate_rational", _rational, f"WITH e AS ({W.estimates_sql(SUP_SQL, SMALL)}) " + " UNION ALL ".join(map(_rational_sql, (P.HAMMING, P.ROGERS_TANIMOTO, P.DICE))))


def _corrected(s, d):
    _, _, c = W.parts(SUP, SMALL)(s, d)
    used = sketch.packed(c, SMALL).select("set_id", "level", F.aggregate("words", F.lit(0).cast("long"), lambda a, w: a + F.bit_count(w)).alias("n"))
    e = W.estimated(SUP, SMALL)(s, d)
    a, b = used.withColumnsRenamed({"set_id": "left_id", "n": "na"}), used.withColumnsRenamed({"set_id": "right_id", "n": "nb"})
    rows = e.join(a, ["left_id", "level"], "left").join(b, ["right_id", "level"], "left").na.fill(0, ["na", "nb"])
    return rows.select("left_id", "right_id", F.round(candidates.corrected(F.col("both"), F.col("na"), F.col("nb"), SMALL.buckets), 6).alias("est"))


_items = lambda n: f"(-{SMALL.buckets} * ln(1 - least({n}, {SMALL.buckets - 1})::DOUBLE / {SMALL.buckets}))"
add(
    "estimates_corrected",
    _corrected,
    f"""WITH e AS ({W.estimates_sql(SUP_SQL, SMALL)}), u AS (SELECT set_id, level, count(*) AS n FROM ({W.cells_sql(SUP_SQL, SMALL)}) GROUP BY 1, 2),
        j AS (SELECT e.*, coalesce(a.n, 0) AS na, coalesce(b.n, 0) AS nb FROM e LEFT JOIN u a ON a.set_id = left_id AND a.level = e.level LEFT JOIN u b ON b.set_id = right_id AND b.level = e.level)
        SELECT left_id, right_id, CASE WHEN {_items('na + nb - "both"')} = 0 THEN 1.0 ELSE round(({_items('na')} + {_items('nb')} - {_items('na + nb - "both"')}) / {_items('na + nb - "both"')}, 6) END AS est FROM j""",
)


def _unfiltered(s, d):
    """Estimates of every pair of suppliers, without a filter."""
    _, cards, c = W.parts(SUP, SMALL)(s, d)
    out = candidates.estimate_all(sketch.packed(c, SMALL), cards, SMALL)
    return out.withColumn("est", F.round("est", 6))


add(
    "estimates_all_pairs",
    _unfiltered,
    W.estimates_sql(SUP_SQL, SMALL).replace(f"pairs AS ({W.candidates_sql(SUP_SQL, SMALL)})", "pairs AS (SELECT a.set_id AS left_id, b.set_id AS right_id FROM cards a JOIN cards b ON a.set_id < b.set_id)"),
)
add(
    "sensitivity_curve",
    lambda s, d: evaluate.sensitivity_curve(*W.by_class(LIVE, SMALL)(s, d)[:2]),
    f"""SELECT (inter * 20 // uni)::BIGINT AS bin, count(*) AS pairs, count(f.left_id) AS hits FROM ({W.pairs_sql(W.net_sql(LIVE_SQL))}) e
        LEFT JOIN ({W.candidates_sql(LIVE_SQL, SMALL)}) f USING (left_id, right_id) GROUP BY 1""",
)

# --- upkeep, order, density -----------------------------------------------------------------------------------------------


def _upkeep(s, d):
    """A stored sketch brought up to date by the sketch of what came since."""
    u = LIVE(s, d)
    return sketch.merged(sketch.cells(u.where("ts < timestamp_ntz'2024-01-16'"), SMALL), sketch.cells(u.where("ts >= timestamp_ntz'2024-01-16'"), SMALL))


add("sketch_upkeep", _upkeep, W.cells_sql(LIVE_SQL, SMALL))
add("sketch_midstream", lambda s, d: sketch.cells(LIVE(s, d).where("ts < timestamp_ntz'2024-01-16'"), SMALL), W.cells_sql(f"SELECT * FROM ({LIVE_SQL}) WHERE ts < TIMESTAMP '2024-01-16'", SMALL))
add(
    "coarse_items",
    lambda s, d: updates.net_sets(updates.map_items(W.returns(s, d), views.table(s, d, "part").select(F.col("p_partkey").alias("item_id"), F.col("p_size").cast("long").alias("coarse_id")))),
    W.net_sql(f"SELECT set_id, p_size::BIGINT AS item_id, delta FROM ({W.RETURNS}) JOIN part ON p_partkey = item_id"),
)
add(
    "online_minhash",
    lambda s, d: baselines.online_minhash(updates.to_transitions(LIVE(s, d)), SMALL).select("set_id", F.array_join("sig", "-").alias("sig")),
    f"SELECT set_id, sig FROM ({W.plain_sql(W.net_sql(LIVE_SQL), SMALL)})",
)
add(
    "eager_equals_lazy",
    lambda s, d: maintain.eager_signatures(LIVE(s, d), SMALL).select("set_id", "level", F.array_join("sig", "-").alias("sig")),
    f"SELECT set_id, level, string_agg(band_key, '-' ORDER BY band) AS sig FROM ({W.bands_sql(LIVE_SQL, SMALL)}) GROUP BY 1, 2",
)
add("dictionary_ids", lambda s, d: synthetic.dictionary(views.table(s, d, "part").select(F.col("p_type").alias("item_key")).union(views.table(s, d, "part").select("p_brand"))), "SELECT item_key, row_number() OVER (ORDER BY item_key) AS item_id FROM (SELECT p_type AS item_key FROM part UNION SELECT p_brand FROM part)")

# --- hashing and theory ---------------------------------------------------------------------------------------------------

FIELD = (1 << 61) - 1
AB = [(a * 2654435761 % FIELD, b * 40503 % FIELD) for a, b in SMALL.draw("field", 4)]
add(
    "hash_field",
    lambda s, d: views.supplier_parts(s, d).select("item_id").distinct().select("item_id", *[field_hash(F.col("item_id"), ab).alias(f"h{i}") for i, ab in enumerate(AB)]),
    "SELECT DISTINCT l_partkey AS item_id, " + ", ".join(f"(({a}::HUGEINT * l_partkey + {b}) % {FIELD})::BIGINT AS h{i}" for i, (a, b) in enumerate(AB)) + " FROM lineitem",
)
DRAWS = SMALL.draw("independence", 48)


def _independence(s, d):
    """How often two items meet in one of 16 buckets, over many draws; independence in pairs says once in 16."""
    x = views.table(s, d, "supplier").select(hash_input(F.col("s_suppkey")).alias("x"))
    own = x.select(F.posexplode(F.array(*[shift_hash(F.col("x"), ab, 4) for ab in DRAWS])).alias("draw", "h"))
    met = own.groupBy("draw", "h").agg(F.count("*").alias("n")).groupBy("draw").agg(F.sum(F.expr("n * (n - 1) div 2")).alias("met"), F.sum("n").alias("items"))
    return met.select("draw", "met", F.expr("items * (items - 1) div 2").alias("pairs"))


_x = "('0x' || substr(md5(s_suppkey::VARCHAR), 1, 7))::BIGINT"
add(
    "hash_independence",
    _independence,
    f"""SELECT draw::INTEGER AS draw, sum(n * (n - 1) // 2)::BIGINT AS met, (sum(n) * (sum(n) - 1) // 2)::BIGINT AS pairs FROM (SELECT draw, h, count(*)::BIGINT AS n FROM (
        {' UNION ALL '.join(f"SELECT {i} AS draw, {W.hash_sql(_x, ab, 4)} AS h FROM supplier" for i, ab in enumerate(DRAWS))}) GROUP BY 1, 2) GROUP BY 1""",
)
SEEDS = [P.SketchParams(log_m=12, buckets=128, seed=i) for i in range(6)]


def _lemma(s, d):
    """Over hash draws: how many pairs' similarity in a sample of one level is within 1 +- 1/2 of the exact one, and the
    sum of squares by which sampled intersections deviate from their expectation."""
    x = hash_input(F.col("item_id"))
    deep = [level_of(shift_hash(x, p.draw("level", 1)[0], p.log_m), p.log_m) > 2 for p in SEEDS]
    marks = sum((F.when(c, 1 << i).otherwise(0) for i, c in enumerate(deep)), F.lit(0))
    rows = blocks.exact_pairs(views.supplier_parts(s, d), marks, len(SEEDS))
    own = []
    for i in range(len(SEEDS)):
        zi, zu = F.col(f"zi{i}"), F.col(f"zu{i}")
        near = (2 * zi * F.col("uni") <= 3 * zu * F.col("inter")) & (2 * zi * F.col("uni") >= zu * F.col("inter"))
        own += [F.count_if(near).alias(f"near{i}"), F.sum((4 * zi - F.col("inter")) * (4 * zi - F.col("inter"))).alias(f"squares{i}")]
    sums = rows.agg(F.count("*").alias("pairs"), *own)
    one = lambda i, p: F.struct(F.lit(p.seed).alias("seed"), F.col("pairs"), F.col(f"near{i}").alias("near"), F.col(f"squares{i}").alias("squares"))
    return sums.select(F.inline(F.array(*[one(i, p) for i, p in enumerate(SEEDS)])))


_sample_sql = lambda p: f"SELECT set_id, item_id FROM ({W.placed_sql(W.VIEW_SQL['supplier_parts'], p)}) WHERE level > 2"
add(
    "sampling_lemma",
    _lemma,
    " UNION ALL ".join(
        f"""SELECT {p.seed} AS seed, count(*) AS pairs, count(*) FILTER (2 * zi * uni <= 3 * zu * inter AND 2 * zi * uni >= zu * inter) AS near, sum((4 * zi - inter) * (4 * zi - inter))::BIGINT AS squares FROM (
        SELECT e.inter, e.uni, coalesce(z.inter, 0) AS zi, coalesce(z.uni, 0) AS zu FROM ({W.pairs_sql(W.VIEW_SQL['supplier_parts'])}) e LEFT JOIN ({W.pairs_sql(_sample_sql(p))}) z USING (left_id, right_id))"""
        for p in SEEDS
    ),
)


def _calculators(s, d):
    """What the calculators say for every setting that the order lines name."""
    li = views.table(s, d, "lineitem").select((F.col("l_linenumber") / 10).alias("eps"), (F.col("l_discount") + 0.1).alias("delta"), (F.col("l_quantity") / 51).alias("r1"), (F.col("l_tax") / 10).alias("r2")).distinct()
    eps, delta, r1, r2 = (F.col(c) for c in ("eps", "delta", "r1", "r2"))
    _, _, p1, p2 = P.sensitivity(eps, delta, r1, r2)
    lo, hi = P.ratio_bounds(eps)
    own = {"alpha": P.theory_alpha(eps, delta) * 1000, "buckets": F.log2(P.theory_buckets(eps, delta, r1)), "samples": F.log2(P.sample_bound(eps, delta, r1)), "p1": p1, "p2": p2, "gray": P.gray_zone(r1), "low": lo, "high": hi}
    return li.select("eps", "delta", "r1", "r2", *[F.round(c, 6).alias(n) for n, c in own.items()])


add(
    "calculators",
    _calculators,
    """SELECT eps, delta, r1, r2, round(eps * eps * delta / 600 * 1000, 6) AS alpha, round(log2(1 / (pow(eps, 4) * pow(delta, 5) * r1 * r1)), 6) AS buckets, round(log2(1800 / (eps * eps * delta * delta * r1)), 6) AS samples,
        round((1 - eps) * r1, 6) AS p1, round(6 * r2 / (delta * (1 - eps / 5 * sqrt(2 * r1))), 6) AS p2, round(pow(r1, 1.5), 6) AS gray, round((1 - eps) / (1 + eps), 6) AS low, round((1 + eps) / (1 - eps), 6) AS high
        FROM (SELECT DISTINCT l_linenumber / 10.0::DOUBLE AS eps, l_discount + 0.1::DOUBLE AS delta, l_quantity / 51.0::DOUBLE AS r1, l_tax / 10.0::DOUBLE AS r2 FROM lineitem)""",
)
CURVES = ((4, 400), (5, 50), (5, 150), (5, 300), (5, 320), (6, 200))


def _neighbours(s, d, steps):
    """set_id, step, inter, uni of each user and those whose id is larger by a step."""
    view = views.user_topics(s, d)
    card = updates.cardinalities(view)
    ahead = F.explode(F.array(*map(F.lit, steps))).alias("step")
    a = card.select("set_id", F.col("card").alias("a"), ahead)
    both = a.join(card.select(F.col("set_id").alias("other"), F.col("card").alias("b")), F.col("set_id") + F.col("step") == F.col("other")).select("set_id", "step", "a", "b")
    mine = view.select("set_id", "item_id", ahead).withColumn("other", F.col("set_id") + F.col("step"))
    met = mine.join(view.withColumnRenamed("set_id", "other"), ["other", "item_id"]).groupBy("set_id", "step").agg(F.count("*").alias("n"))
    rows = both.join(met, ["set_id", "step"], "left").withColumn("inter", F.coalesce("n", F.lit(0)))
    return blocks.stored(rows.select("set_id", "step", "inter", (F.col("a") + F.col("b") - F.col("inter")).alias("uni")), "neighbours")


def _neighbours_sql(steps) -> str:
    return f"""SELECT c.set_id, step, coalesce(n, 0) AS inter, c.card + o.card - coalesce(n, 0) AS uni FROM ({W.cards_sql(W.VIEW_SQL['user_topics'])}) c, (VALUES {', '.join(f'({k})' for k in steps)}) AS t(step)
        JOIN ({W.cards_sql(W.VIEW_SQL['user_topics'])}) o ON o.set_id = c.set_id + step
        LEFT JOIN (SELECT x.set_id, k AS step, count(*) AS n FROM ({W.VIEW_SQL['user_topics']}) x, (VALUES {', '.join(f'({k})' for k in steps)}) AS u(k) JOIN ({W.VIEW_SQL['user_topics']}) y ON y.set_id = x.set_id + k AND y.item_id = x.item_id GROUP BY 1, 2) m ON m.set_id = c.set_id AND m.step = t.step""".replace("SELECT c.set_id, step,", "SELECT c.set_id, t.step,")


def _curve(s, d):
    """Chance of each setting to report a user with the next one."""
    sim = F.col("inter") / F.col("uni")
    one = lambda l, m: F.struct(F.lit(l).alias("l"), F.lit(m).alias("m"), F.round(P.detect_probability(sim, l, m), 6).alias("p"))
    return _neighbours(s, d, (1,)).select("set_id", F.inline(F.array(*[one(l, m) for l, m in CURVES])))


add("detect_curve", _curve, f"SELECT set_id, l::INTEGER AS l, m::INTEGER AS m, round(1 - pow(1 - pow(inter::DOUBLE / uni, l), m), 6) AS p FROM ({_neighbours_sql((1,))}), (VALUES {', '.join(map(str, CURVES))}) v(l, m)")


def _flags(s, d):
    """Which presets are metrics and have a sensitive family, and how many triples of users (three ids in a row) break the
    triangle inequality."""
    n = _neighbours(s, d, (1, 2))
    far = lambda x, m: 1 - similarity.rational_similarity(F.col(f"{x}.inter"), F.col(f"{x}.uni"), F.col(f"{x}.uni") - F.col(f"{x}.inter"), F.lit(100), m)
    k = n.groupBy("set_id").pivot("step", [1, 2]).agg(F.first(F.struct("inter", "uni")))
    rows = k.select("set_id", F.col("1").alias("ab"), F.col("2").alias("ac")).join(k.select((F.col("set_id") - 1).alias("set_id"), F.col("1").alias("bc")), "set_id").where("ab is not null and ac is not null and bc is not null")
    broken = [F.count_if(far("ac", m) > far("ab", m) + far("bc", m) + 1e-9).alias(m.name) for m in P.PRESETS]
    sums = rows.agg(F.count("*").alias("triples"), *broken)
    one = lambda m: F.struct(F.lit(m.name).alias("name"), F.lit(m.is_metric).alias("is_metric"), F.lit(m.is_lshable()).alias("lshable"), F.lit(m.is_lshable(0.5)).alias("root_lshable"), F.col("triples"), F.col(m.name).alias("broken"))
    return sums.select(F.inline(F.array(*map(one, P.PRESETS))))


def _far_sql(x: str, m: P.Similarity) -> str:
    base, apart = f"({m.x} * {x}.inter + {m.y} * (100 - {x}.uni))", f"({x}.uni - {x}.inter)"
    return f"(1 - CASE WHEN {base} + {m.zp} * {apart} = 0 THEN 1.0 ELSE ({base} + {m.z} * {apart})::DOUBLE / ({base} + {m.zp} * {apart}) END)"


add(
    "metric_flags",
    _flags,
    f"WITH n AS ({_neighbours_sql((1, 2))}), t AS (SELECT {', '.join(f'{_far_sql(chr(97) + chr(99), m)} > {_far_sql(chr(97) + chr(98), m)} + {_far_sql(chr(98) + chr(99), m)} + 1e-9 AS {m.name}' for m in P.PRESETS)} FROM n ab JOIN n ac ON ac.set_id = ab.set_id AND ab.step = 1 AND ac.step = 2 JOIN n bc ON bc.set_id = ab.set_id + 1 AND bc.step = 1) "
    + " UNION ALL ".join(f"SELECT '{n}' AS name, {m} AS is_metric, {l} AS lshable, {r} AS root_lshable, count(*) AS triples, count(*) FILTER ({n}) AS broken FROM t" for n, m, l, r in (("jaccard", "true", "true", "true"), ("hamming", "true", "true", "true"), ("anderberg", "true", "true", "true"), ("rogers_tanimoto", "true", "true", "true"), ("dice", "false", "false", "false"))),
)

# --- linear sketches and distances ----------------------------------------------------------------------------------------

L0, REPS = W.L0, 2


def _estimate_sql(cells: str, by: str) -> str:
    k = L0.buckets
    return f"""SELECT {by}, median(coalesce(est, top)) AS items FROM (SELECT {by}, rep, min_by(items, k) FILTER (used <= {0.7 * k!r}) AS est, max_by(items, k) AS top FROM (
        SELECT {by}, rep, k, used, -{float(k)} * ln(1 - least(used, {k - 1})::DOUBLE / {k}) * pow(2.0, k - 1) AS items FROM (
        SELECT {by}, rep, k, count(DISTINCT bucket) AS used FROM (SELECT {by}, rep, bucket, unnest(range(1, level + 1)) AS k FROM ({cells})) GROUP BY ALL)) GROUP BY ALL) GROUP BY ALL"""


def _combined_sql(sign: int) -> str:
    total = f"((sum(cell) % {l0.PRIME}) + {l0.PRIME}) % {l0.PRIME}"
    return f"""SELECT left_id, right_id, rep, level, bucket, ({total})::BIGINT AS cell FROM (SELECT left_id, right_id, rep, level, bucket, cell FROM p JOIN c ON set_id = left_id
        UNION ALL SELECT left_id, right_id, rep, level, bucket, {sign} * cell FROM p JOIN c ON set_id = right_id) GROUP BY ALL HAVING {total} <> 0"""


_size_ctes = f"""c AS ({W.l0_sql(LIVE_SQL, L0, REPS)}), p AS (SELECT left_id, right_id FROM ({W.pairs_sql(W.net_sql(LIVE_SQL))})),
    u AS ({_estimate_sql(_combined_sql(1), 'left_id, right_id')}), a AS ({_estimate_sql(_combined_sql(-1), 'left_id, right_id')}),
    z AS (SELECT left_id, right_id, coalesce(u.items, 0) AS uni, coalesce(a.items, 0) AS symdiff FROM p LEFT JOIN u USING (left_id, right_id) LEFT JOIN a USING (left_id, right_id))"""


def _pairs_and_sketch(s, d):
    stream = LIVE(s, d)
    return similarity.exact_pairs(updates.net_sets(stream)).select("left_id", "right_id"), l0.l0_cells(stream, L0, REPS)


add("l0_cardinalities", lambda s, d: l0.l0_estimate(_pairs_and_sketch(s, d)[1], ["set_id"], L0).select("set_id", F.round("items", 4).alias("items")), f"SELECT set_id, round(items, 4) AS items FROM ({_estimate_sql(W.l0_sql(LIVE_SQL, L0, REPS), 'set_id')})")


def _sizes(s, d):
    pairs, sk = _pairs_and_sketch(s, d)
    return l0.sizes(pairs, sk, L0).select("left_id", "right_id", F.round("uni", 4).alias("uni"), F.round("symdiff", 4).alias("symdiff"))


add("l0_sizes", _sizes, f"WITH {_size_ctes} SELECT left_id, right_id, round(uni, 4) AS uni, round(symdiff, 4) AS symdiff FROM z")
#: A similarity that weighs what neither set has more than what both have goes by complements.
ABSENT = P.Similarity("absent", 0, 1, 0, 1)
MEASURED = ((P.JACCARD, 1.0), (P.JACCARD, 0.5), (P.HAMMING, 1.0), (P.ANDERBERG, 1.0), (P.ROGERS_TANIMOTO, 1.0), (P.DICE, 1.0), (ABSENT, 1.0))
UNIVERSE = 100


def _distances(s, d):
    pairs, sk = _pairs_and_sketch(s, d)
    one = lambda m, a: F.struct(F.lit(f"{m.name} {a}").alias("name"), F.round(l0.distance_of(F.col("uni"), F.col("symdiff"), UNIVERSE, m, a), 5).alias("distance"))
    return l0.sizes(pairs, sk, L0).select("left_id", "right_id", F.inline(F.array(*[one(m, a) for m, a in MEASURED])))


def _distance_sql(m: P.Similarity, a: float) -> str:
    den = f"{m.y} * {UNIVERSE} + ({m.x - m.y}) * uni + ({m.zp - m.x}) * symdiff"
    if m.y > m.x:
        den = f"{m.y - m.x} * ({UNIVERSE} - greatest(uni - symdiff, 0.0)) + {m.x} * {UNIVERSE} + ({m.zp - m.y}) * symdiff"
    return f"SELECT left_id, right_id, '{m.name} {a}' AS name, round(pow(CASE WHEN {den} <= 0 THEN 0.0 ELSE least(1.0, {m.zp - m.z} * symdiff / ({den})) END, {a}), 5) AS distance FROM z"


add("l0_distances", _distances, f"WITH {_size_ctes} " + " UNION ALL ".join(_distance_sql(m, a) for m, a in MEASURED))


def _exact_distances(s, d):
    pairs = similarity.class_pairs(views.user_topics(s, d))
    inter, uni = F.col("inter"), F.col("uni")
    one = lambda m: F.struct(F.lit(m.name).alias("name"), F.round(1 - similarity.rational_similarity(inter, uni, uni - inter, F.lit(100), m), 6).alias("distance"))
    return pairs.select("left_id", "right_id", "same", F.inline(F.array(*[one(m) for m in (*P.PRESETS, ABSENT)])))


add(
    "distance_presets",
    _exact_distances,
    f"WITH p AS ({W.class_pairs_sql(W.VIEW_SQL['user_topics'])}) "
    + " UNION ALL ".join(
        f"SELECT left_id, right_id, same, '{m.name}' AS name, CASE WHEN {m.x} * inter + {m.y} * (100 - uni) + {m.zp} * (uni - inter) = 0 THEN 0.0 ELSE round(1 - ({m.x} * inter + {m.y} * (100 - uni) + {m.z} * (uni - inter))::DOUBLE / ({m.x} * inter + {m.y} * (100 - uni) + {m.zp} * (uni - inter)), 6) END AS distance FROM p"
        for m in (*P.PRESETS, ABSENT)
    ),
)
add(
    "vec_lp_norms",
    lambda s, d: views.table(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v")).select("vec_id", *[F.round(similarity.lp_norm(F.col("v"), p), 6).alias(f"l{p}") for p in (0, 1, 2)]),
    """SELECT vec_id, len(list_filter(v, lambda x: x <> 0))::DOUBLE AS l0, round(list_sum(list_transform(v, lambda x: abs(x))), 6) AS l1, round(sqrt(list_sum(list_transform(v, lambda x: x * x))), 6) AS l2
        FROM (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings)""",
)

# --- profiles -------------------------------------------------------------------------------------------------------------


def _genre_cosine(s, d):
    """Of pairs of users: similarity by items and by genres."""
    log = views.event_topics(s, d)
    v = applications.genre_profiles(log)
    norm = v.groupBy("set_id").agg(F.sqrt(F.sum(F.col("share") * F.col("share"))).alias("n"))
    a, b = v.withColumnsRenamed({"set_id": "left_id", "share": "p"}), v.withColumnsRenamed({"set_id": "right_id", "share": "q"})
    dot = a.join(b, "genre").where("left_id < right_id").groupBy("left_id", "right_id").agg(F.sum(F.col("p") * F.col("q")).alias("dot"))
    m, n = norm.withColumnsRenamed({"set_id": "left_id", "n": "m"}), norm.withColumnRenamed("set_id", "right_id")
    items = similarity.exact_pairs(views.user_topics(s, d))
    rows = items.join(dot, ["left_id", "right_id"]).join(m, "left_id").join(n, "right_id")
    return rows.select("left_id", "right_id", F.round(F.col("inter") / F.col("uni"), 6).alias("by_items"), F.round(F.col("dot") / (F.col("m") * F.col("n")), 4).alias("by_genres"))


add(
    "genre_cosine",
    _genre_cosine,
    f"""WITH v AS ({W._GENRES}), n AS (SELECT set_id, sqrt(sum(share * share)) AS n FROM v GROUP BY 1), d AS (SELECT a.set_id AS left_id, b.set_id AS right_id, sum(a.share * b.share) AS dot FROM v a JOIN v b USING (genre) WHERE a.set_id < b.set_id GROUP BY 1, 2)
        SELECT e.left_id, e.right_id, round(inter::DOUBLE / uni, 6) AS by_items, round(dot / (m.n * k.n), 4) AS by_genres FROM ({W.pairs_sql(W.VIEW_SQL['user_topics'])}) e JOIN d USING (left_id, right_id) JOIN n m ON m.set_id = e.left_id JOIN n k ON k.set_id = e.right_id""",
)


def _heatmap(s, d):
    """The showcase users' distances in the order of their tree's leaves."""
    ids = sorted(r.set_id for r in W._show(s, d).collect())  # a showcase, at most SELECTION
    m = applications.matrix_of(W.exact(LIVE)(s, d).withColumn("distance", 1 - F.col("inter") / F.col("uni")), ids)
    return applications.heatmap_rows(s, m, applications.leaf_order(applications.hierarchical(m, "average"), m))


add("ordered_heatmap", _heatmap, None)

# --- the synthetic benchmark ----------------------------------------------------------------------------------------------

BANDS = (0.4, 0.5, 0.6, 0.7, 0.8, 0.9)
add("synthetic_rows", lambda s, d: synthetic.rows(views.supplier_parts(s, d), 10_000), synthetic.rows_sql(W.VIEW_SQL['supplier_parts'], 10_000))
add("synthetic_stream", lambda s, d: updates.with_random_deletions(updates.insert_stream(synthetic.planted(views.supplier_parts(s, d), 10_000, BANDS))).select("set_id", "item_id", "delta", "seq"), W.thinned_sql(synthetic.planted_sql(W.VIEW_SQL['supplier_parts'], 10_000, BANDS)).replace("1 AS delta, 0 AS seq", "1::INTEGER AS delta, 0::BIGINT AS seq"))


def _bands(s, d):
    """How alike the planted rows are to those that they were made of."""
    view = synthetic.planted(views.supplier_parts(s, d), 10_000, BANDS)
    made = F.col("set_id") >= synthetic.SHIFT
    a = view.where(~made).withColumnRenamed("set_id", "base_id")
    b = view.where(made).withColumn("base_id", F.col("set_id") - synthetic.SHIFT)
    both = a.join(b, ["base_id", "item_id"]).groupBy("base_id").agg(F.count("*").alias("inter"))
    size = lambda x, n: x.groupBy("base_id").agg(F.count("*").alias(n))
    rows = both.join(size(a, "na"), "base_id").join(size(b, "nb"), "base_id")
    return rows.select("base_id", "inter", (F.col("na") + F.col("nb") - F.col("inter")).alias("uni"))


add(
    "synthetic_bands",
    _bands,
    f"""WITH v AS ({synthetic.planted_sql(W.VIEW_SQL['supplier_parts'], 10_000, BANDS)}), a AS (SELECT set_id AS base_id, item_id FROM v WHERE set_id < {synthetic.SHIFT}), b AS (SELECT set_id - {synthetic.SHIFT} AS base_id, item_id FROM v WHERE set_id >= {synthetic.SHIFT}),
        n AS (SELECT base_id, count(*) AS inter FROM a JOIN b USING (base_id, item_id) GROUP BY 1)
        SELECT base_id, inter, (SELECT count(*) FROM a WHERE a.base_id = n.base_id) + (SELECT count(*) FROM b WHERE b.base_id = n.base_id) - inter AS uni FROM n""",
)
PRINTED = P.SketchParams(log_m=16, buckets=512, alpha=0.05, r1=0.5, rows=5, bands=40)


def _synthetic_quality(s, d):
    """Recall by band of planted pairs of all suppliers in 10,000 columns with a tenth removed."""
    view = synthetic.planted(views.supplier_parts(s, d), 10_000, BANDS)
    stream = updates.with_random_deletions(updates.insert_stream(view))
    net = updates.net_sets(stream)
    found = candidates.find_pairs(net, sketch.cells(stream, PRINTED), updates.cardinalities(net), PRINTED)
    truth = view.where(F.col("set_id") >= synthetic.SHIFT).select((F.col("set_id") - synthetic.SHIFT).alias("left_id"), F.col("set_id").alias("right_id")).distinct()
    hit = truth.join(found.withColumn("hit", F.lit(1)), ["left_id", "right_id"], "left")
    band = F.element_at(F.array(*map(F.lit, BANDS)), (F.floor(F.col("left_id") / synthetic.EVERY) % len(BANDS) + 1).cast("int"))
    return hit.groupBy(band.alias("band")).agg(F.count("*").alias("planted"), F.count("hit").alias("found"))


add("synthetic_recall", _synthetic_quality, None)

# --- operators around them ------------------------------------------------------------------------------------------------


def _roundtrip(s, d):
    """A table written in each format and read back."""
    from ebbset.session import scratch

    t = views.table(s, d, "supplier").select("s_suppkey", "s_name")
    out = []
    for kind in ("parquet", "orc", "json", "csv"):
        path = scratch(s, f"roundtrip-{kind}")
        t.write.format(kind).save(path)
        back = s.read.schema(t.schema).format(kind).load(path)
        out.append(back.agg(F.lit(kind).alias("kind"), F.count("*").alias("n"), F.sum("s_suppkey").alias("keys"), F.max("s_name").alias("last")))
    return reduce(DataFrame.union, out)


add("scan_formats_roundtrip", _roundtrip, "SELECT kind, count(*) AS n, sum(s_suppkey)::BIGINT AS keys, max(s_name) AS last FROM supplier, (VALUES ('parquet'), ('orc'), ('json'), ('csv')) AS f(kind) GROUP BY 1")


def _salted(s, d):
    """Sums by a hot key in two steps: by key and salt, then by key."""
    li = views.table(s, d, "lineitem").select("l_returnflag", F.pmod(F.col("l_orderkey"), F.lit(16)).alias("salt"), "l_quantity")
    part = li.groupBy("l_returnflag", "salt").agg(F.sum("l_quantity").alias("q"), F.count("*").alias("n"))
    return part.groupBy("l_returnflag").agg(F.round(F.sum("q"), 2).alias("q"), F.sum("n").alias("n"))


add("agg_partial_final", _salted, "SELECT l_returnflag, round(sum(l_quantity), 2) AS q, count(*) AS n FROM lineitem GROUP BY 1")
add("fn_hash_md5", lambda s, d: views.table(s, d, "supplier").select("s_suppkey", F.md5("s_name").alias("md5"), F.sha2("s_name", 256).alias("sha")), "SELECT s_suppkey, md5(s_name) AS md5, sha256(s_name) AS sha FROM supplier")
add("fn_math", lambda s, d: views.table(s, d, "supplier").select("s_suppkey", F.round(F.log2(F.abs("s_acctbal") + 1), 6).alias("log2"), F.round(F.pow(F.abs("s_acctbal"), F.lit(0.3)), 6).alias("pow"), F.ceil("s_acctbal").alias("up"), F.pmod(F.col("s_suppkey"), F.lit(7)).alias("mod"), F.bit_count("s_suppkey").alias("bits")), "SELECT s_suppkey, round(log2(abs(s_acctbal) + 1), 6) AS log2, round(pow(abs(s_acctbal), 0.3), 6) AS pow, ceil(s_acctbal)::BIGINT AS up, s_suppkey % 7 AS mod, bit_count(s_suppkey)::INTEGER AS bits FROM supplier")


def _nested(s, d):
    n = views.table(s, d, "nation").groupBy("n_regionkey").agg(F.sort_array(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("nations"))
    return n.select("n_regionkey", F.size("nations").alias("many"), F.element_at("nations", 1)["n_name"].alias("first"), F.inline("nations").alias("n_nationkey", "n_name"))


add("fn_struct_nested", _nested, "SELECT n_regionkey, count(*) OVER w::INTEGER AS many, first_value(n_name) OVER (w ORDER BY n_nationkey) AS first, n_nationkey, n_name FROM nation WINDOW w AS (PARTITION BY n_regionkey)".replace("OVER w::INTEGER", "OVER (PARTITION BY n_regionkey)").replace("count(*) OVER (PARTITION BY n_regionkey)", "(count(*) OVER (PARTITION BY n_regionkey))::INTEGER").replace("OVER (w ORDER BY", "OVER (PARTITION BY n_regionkey ORDER BY").replace(" WINDOW w AS (PARTITION BY n_regionkey)", ""))


def _log(s, d):
    e = s.readStream.schema(views.table(s, d, "events").schema).parquet(f"{d}/event[s].parquet")
    return e.select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts")).withWatermark("ts", "40 days")


def _drained(stream: DataFrame, mode: str) -> DataFrame:
    return maintain.drained(stream, f"drained_{uuid.uuid4().hex}", mode)


def _day(c: str):
    return F.date_format(c, "yyyy-MM-dd HH").alias("begin")


add(
    "stream_sliding",
    lambda s, d: _drained(_log(s, d).groupBy(F.window("ts", "2 days", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")), "complete").select(_day("w.start"), "event_type", "n"),
    "SELECT strftime(date_trunc('day', ts) - to_days(o::INTEGER), '%Y-%m-%d %H') AS begin, event_type, count(*) AS n FROM events, range(0, 2) AS t(o) GROUP BY 1, 2",
)
add(
    "stream_session",
    lambda s, d: _drained(_log(s, d).groupBy(F.session_window("ts", "1 day").alias("w"), "user_id").agg(F.count("*").alias("n")), "complete").select("user_id", _day("w.start"), "n"),
    """WITH g AS (SELECT *, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 1 DAY THEN 1 ELSE 0 END AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
        r AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS run FROM g)
        SELECT user_id, strftime(min(ts), '%Y-%m-%d %H') AS begin, count(*) AS n FROM r GROUP BY user_id, run""",
)
add(
    "stream_dedup",
    lambda s, d: _drained(_log(s, d).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]), "append"),
    "SELECT DISTINCT user_id, event_type FROM events",
)
add(
    "stream_static_join",
    lambda s, d: maintain.appended(_log(s, d).join(F.broadcast(views.table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("k"), "n_name")), F.col("user_id") % 25 == F.col("k")).select("event_id", "n_name")),
    "SELECT event_id, n_name FROM events JOIN nation ON n_nationkey = user_id % 25",
)


def _intervals(s, d):
    a = _log(s, d).where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("view_id"), F.col("ts").alias("seen"))
    b = _log(s, d).where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("buy_id"), F.col("ts").alias("bought"))
    near = F.expr("u = user_id AND bought >= seen AND bought <= seen + interval 1 day")
    return _drained(a.join(b, near).select("view_id", "buy_id"), "append")


add("stream_stream_interval", _intervals, "SELECT a.event_id AS view_id, b.event_id AS buy_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY WHERE a.event_type = 'view' AND b.event_type = 'purchase'")


def _eager(s, d):
    """Signatures kept by a stateful stream; without removals they equal those of the lazily kept sketch."""
    e = s.readStream.schema(views.table(s, d, "events").schema).parquet(f"{d}/event[s].parquet")
    u = e.select(F.col("user_id").alias("set_id"), F.get_json_object("props", "$.k").cast("long").alias("item_id"), F.lit(1).alias("delta"), F.col("event_id").alias("seq"))
    return _drained(maintain.eager_stream(u, SMALL), "update").select("set_id", "level", F.array_join("sig", "-").alias("sig"))


_ALL = "SELECT user_id AS set_id, (props->>'k')::BIGINT AS item_id, 1 AS delta FROM events"
add("stream_eager_signatures", _eager, f"SELECT set_id, level, string_agg(band_key, '-' ORDER BY band) AS sig FROM ({W.bands_sql(_ALL, SMALL)}) GROUP BY 1, 2")


def _scalar(s, d):
    @F.pandas_udf("long")
    def digits(x: pd.Series) -> pd.Series:
        return x.str.count(r"\d").astype("int64")

    return views.table(s, d, "supplier").select("s_suppkey", digits("s_name").alias("digits"))


add("udf_scalar", _scalar, "SELECT s_suppkey, len(regexp_replace(s_name, '[^0-9]', '', 'g'))::BIGINT AS digits FROM supplier")
add("udf_arrow_signature", lambda s, d: W.banded(SUP, SMALL, native=False)(s, d).select("set_id", "level", "band", "band_key"), f"SELECT set_id, level, band::INTEGER AS band, band_key FROM ({W.bands_sql(SUP_SQL, SMALL)})")


def _udtf(s, d):
    @F.udtf(returnType="word string, place int")
    class Words:
        def eval(self, text: str):
            for i, w in enumerate((text or "").split(" ")):
                yield w, i

    s.udtf.register("split_words", Words)
    views.table(s, d, "part").createOrReplaceTempView("part_words")
    return s.sql("SELECT p_partkey, word, place FROM part_words, LATERAL split_words(p_name)")


add("udtf_shingles", _udtf, "SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word, (generate_subscripts(string_split(p_name, ' '), 1) - 1)::INTEGER AS place FROM part")


def _grouped(s, d):
    import numpy as np
    import pyarrow as pa

    rows = sketch.placed(updates.insert_stream(updates.net_sets(SUP(s, d))), SMALL)

    def one(t: pa.Table) -> pa.Table:
        return pa.table({"set_id": t["set_id"][:1], "used": [len(np.unique(t["bucket"].to_numpy()))], "deepest": [int(t["level"].to_numpy().max())]})

    return rows.select("set_id", "level", "bucket").groupBy("set_id").applyInArrow(one, "set_id long, used long, deepest long")


add("grouped_arrow_sketch", _grouped, f"SELECT set_id, count(DISTINCT bucket) AS used, max(level)::BIGINT AS deepest FROM ({W.placed_sql(W.net_sql(SUP_SQL), SMALL)}) GROUP BY 1")
add(
    "join_band_theta",
    lambda s, d: views.table(s, d, "supplier").alias("a").join(F.broadcast(views.table(s, d, "supplier").alias("b")), F.expr("a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) < 50")).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b")),
    "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) < 50",
)
