"""More of the registry: structures compared row by row, baselines, measures and workloads."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.measures import measured
from ..functions.stored import shared_dir
from ..functions.variates import hash_uniform, py_uniform, sql_uniform
from ..operators import alias as A
from ..operators import classes as C
from ..operators import estimators as E
from ..operators import items as I
from ..operators import order as O
from ..operators import subset as P
from ..operators import tables as T
from ..operators.overlay import range_overlay
from ..operators.prefix import block_prefix_sum, next_at_or_after
from ..operators.store import ClassStore
from ..sources.tables import FIXTURES, LINE_ID, read_stream
from ..streaming import reservoir as R
from ..streaming import state as S
from . import sqlapi
from .queries import DRAWN, LOCAL, META, ORACLE, PROFILE, REJ, SAMPLED, SEED, SHARDED, STATS, add, alias_sql, attempts_sql, big, clock_sql, compressed, day_events, draws_sql, drawn, flat, items, pi, pi_sql, sampled, sharded

u_sql = lambda key: sql_uniform(SEED, key)
ORDERS = FIXTURES["orders"].sql

# ---- compressed table with four items an entry --------------------------------------------------

GROUPED4 = f"""raw AS (WITH {ORDERS} SELECT id, units, (row_number() OVER (ORDER BY id) - 1) // 4 AS rank FROM items),
items AS (SELECT rank AS id, CAST(sum(units) AS BIGINT) AS units FROM raw GROUP BY rank)"""
REJ4 = f"""{GROUPED4}, {STATS}, m AS (SELECT id, units * n AS mass, total AS cap, (units * n + total - 1) // total AS c FROM items, st), r AS (SELECT *, sum(c) OVER (ORDER BY id ROWS UNBOUNDED PRECEDING) - c AS c0 FROM m),
rt AS (SELECT CAST(c0 + j - 1 AS BIGINT) AS bucket, id, CAST(CASE WHEN j < c THEN cap ELSE mass - cap * (c - 1) END AS BIGINT) AS fill, cap FROM r, LATERAL (SELECT unnest(range(1, CAST(c AS BIGINT) + 1)) AS j))"""
add(
    "compressed_r4",
    compressed(4),
    f"""WITH {REJ4}, {attempts_sql(300, 60, '(SELECT count(*) FROM rt)')}, ok AS (SELECT draw, attempt, id FROM a JOIN rt USING (bucket) WHERE u * CAST(cap AS DOUBLE) <= CAST(fill AS DOUBLE)),
f AS (SELECT draw, arg_min(id, attempt) AS rank FROM ok GROUP BY draw),
g AS (SELECT draw, raw.id, row_number() OVER (PARTITION BY draw ORDER BY raw.id) AS i, sum(raw.units) OVER (PARTITION BY draw ORDER BY raw.id ROWS UNBOUNDED PRECEDING) AS cum, sum(raw.units) OVER (PARTITION BY draw) AS whole, count(*) OVER (PARTITION BY draw) AS m FROM f JOIN raw USING (rank))
SELECT draw, arg_min(id, i) AS id FROM g WHERE CAST(cum AS DOUBLE) >= {u_sql("'inside:' || draw")} * CAST(whole AS DOUBLE) OR i = m GROUP BY draw""",
)
add(
    "accept_rate_table",
    lambda s, d: T.rejection_table(items("orders")(s, d)).agg(F.count("*").alias("buckets"), F.round(F.sum("fill").cast("double") / (F.count("*") * F.max("cap").cast("double")), 9).alias("rate")),
    f"WITH {REJ} SELECT count(*) AS buckets, round(CAST(sum(fill) AS DOUBLE) / (count(*) * CAST(max(cap) AS DOUBLE)), 9) AS rate FROM rt",
)

# ---- two levels, row by row ------------------------------------------------------------------------

add(
    "twolevel_draw",
    lambda s, d: T.twolevel_draw(*T.twolevel_build(sharded(s, d)), 1000, SEED),
    f"""WITH top AS (SELECT *, row_number() OVER (ORDER BY shard) - 1 AS bucket FROM ({META} SELECT id AS shard, part, alias, cap FROM tab)),
loc AS (SELECT *, row_number() OVER (PARTITION BY shard ORDER BY id) - 1 AS bucket, count(*) OVER (PARTITION BY shard) AS m FROM ({LOCAL} SELECT shard, id, part, alias, cap FROM tab)),
p AS (SELECT count(*) AS p FROM top),
q AS (SELECT i AS draw, least(CAST(floor({u_sql("'bucket:' || i")} * p) AS BIGINT), p - 1) AS bucket, {u_sql("'coin:' || i")} AS u FROM range(1000) r(i), p),
sh AS (SELECT draw, CASE WHEN u * CAST(cap AS DOUBLE) >= CAST(part AS DOUBLE) THEN coalesce(alias, shard) ELSE shard END AS shard FROM q JOIN top USING (bucket)),
a AS (SELECT draw, sh.shard, least(CAST(floor({u_sql("'local:' || draw")} * m) AS BIGINT), m - 1) AS bucket, {u_sql("'localcoin:' || draw")} AS u FROM sh JOIN (SELECT DISTINCT shard, m FROM loc) z ON z.shard = sh.shard)
SELECT draw, a.shard, CASE WHEN u * CAST(cap AS DOUBLE) >= CAST(part AS DOUBLE) THEN coalesce(alias, id) ELSE id END AS id FROM a JOIN loc ON loc.shard = a.shard AND loc.bucket = a.bucket""",
)
PIECES = f"""WITH {SHARDED}, t AS (SELECT shard, CAST(sum(units) AS BIGINT) AS own FROM items GROUP BY shard),
mt AS (SELECT shard, own * (SELECT count(*) FROM t) AS mass, (SELECT sum(own) FROM t) AS cap FROM t),
f AS (SELECT shard AS bucket, sum(free) OVER (ORDER BY shard) - free AS a, sum(free) OVER (ORDER BY shard) AS b FROM (SELECT shard, CASE WHEN mass <= cap THEN cap - mass ELSE cap END AS free FROM mt) WHERE free > 0),
h AS (SELECT shard AS owner, sum(mass) OVER (ORDER BY shard) - mass AS a, sum(mass) OVER (ORDER BY shard) AS b FROM mt WHERE mass > cap),
pc AS (SELECT shard AS bucket, shard AS owner, CAST(mass AS BIGINT) AS piece FROM mt WHERE mass <= cap UNION ALL SELECT f.bucket, h.owner, CAST(least(f.b, h.b) - greatest(f.a, h.a) AS BIGINT) FROM f JOIN h ON f.a < h.b AND h.a < f.b)"""
add("twoalias_pieces", lambda s, d: T.twoalias_pieces(T.meta_weights(sharded(s, d))).select("bucket", "owner", *big("piece")), f"{PIECES} SELECT bucket, owner, piece FROM pc")
add(
    "twoalias_bucket_shape",
    lambda s, d: T.twoalias_pieces(T.meta_weights(sharded(s, d))).groupBy("bucket").agg(F.sum("piece").cast("long").alias("held"), F.count_if(F.col("owner") == F.col("bucket")).alias("own"), F.count_if(F.col("owner") != F.col("bucket")).alias("foreign")),
    f"{PIECES} SELECT bucket, CAST(sum(piece) AS BIGINT) AS held, count(*) FILTER (WHERE owner = bucket) AS own, count(*) FILTER (WHERE owner <> bucket) AS foreign FROM pc GROUP BY bucket",
)
add(
    "twoalias_draw",
    lambda s, d: T.twoalias_draw(T.twoalias_pieces(T.meta_weights(sharded(s, d))), 1000, SEED),
    f"""{PIECES}, bx AS (SELECT bucket, row_number() OVER (ORDER BY bucket) - 1 AS ix, sum(piece) AS cap FROM pc GROUP BY bucket),
px AS (SELECT bucket, owner, row_number() OVER w AS i, sum(piece) OVER w AS cum, count(*) OVER (PARTITION BY bucket) AS m FROM pc WINDOW w AS (PARTITION BY bucket ORDER BY owner, piece ROWS UNBOUNDED PRECEDING)),
q AS (SELECT i AS draw, least(CAST(floor({u_sql("'bucket:' || i")} * (SELECT count(*) FROM bx)) AS BIGINT), (SELECT count(*) FROM bx) - 1) AS ix, {u_sql("'coin:' || i")} AS u FROM range(1000) r(i))
SELECT draw, arg_min(owner, px.i) AS shard FROM q JOIN bx USING (ix) JOIN px USING (bucket) WHERE u * CAST(cap AS DOUBLE) <= CAST(cum AS DOUBLE) OR px.i = m GROUP BY draw""",
)
add(
    "rebalance_load",
    lambda s, d: T.rebalance_heavy(sharded(s, d), 16, 0.05).groupBy("shard").agg(F.sum("piece").cast("long").alias("mass"), F.count("*").alias("pieces")),
    f"""WITH {SHARDED}, st AS (SELECT CAST(sum(units) AS BIGINT) AS total FROM items), lim AS (SELECT CAST(0.05 AS DOUBLE) * CAST(total AS DOUBLE) / 64.0 AS lim FROM st),
bg AS (SELECT id, units * 16 AS mass, sum(units * 16) OVER (ORDER BY id) AS b FROM items, lim WHERE CAST(units AS DOUBLE) > lim),
sm AS (SELECT shard, units * 16 AS mass FROM items, lim WHERE CAST(units AS DOUBLE) <= lim),
fr AS (SELECT x.s AS shard, greatest(0, total - coalesce(l, 0)) AS free FROM range(16) x(s) LEFT JOIN (SELECT shard, sum(mass) AS l FROM sm GROUP BY shard) y ON y.shard = x.s, st),
sh AS (SELECT greatest(0, coalesce((SELECT sum(mass) FROM bg), 0) - (SELECT sum(free) FROM fr)) AS short),
fx AS (SELECT shard, free + (short + 15) // 16 AS free FROM fr, sh),
f AS (SELECT shard, sum(free) OVER (ORDER BY shard) - free AS a, sum(free) OVER (ORDER BY shard) AS b FROM fx WHERE free > 0),
al AS (SELECT shard, mass FROM sm UNION ALL SELECT f.shard, least(f.b, bg.b) - greatest(f.a, bg.b - bg.mass) FROM f JOIN bg ON f.a < bg.b AND bg.b - bg.mass < f.b)
SELECT CAST(shard AS INTEGER) AS shard, CAST(sum(mass) AS BIGINT) AS mass, count(*) AS pieces FROM al GROUP BY shard""",
)
SHARD8 = f"CAST(least(7, floor({sql_uniform(0, chr(39) + 'shard:' + chr(39) + ' || id')} * 8)) AS INTEGER)"
add("random_shard_load", lambda s, d: T.load_profile(I.random_shard(items("orders")(s, d), 8, portable=True), F.col("units")).select("shard", "items", *big("load")), f"WITH {ORDERS} SELECT {SHARD8} AS shard, count(*) AS items, CAST(sum(units) AS BIGINT) AS load FROM items GROUP BY 1")
add("sample_load", lambda s, d: C.sample_load(drawn("orders", 1000)(s, d), 8), f"{DRAWN} SELECT {SHARD8} AS shard, count(*) AS draws, count(DISTINCT id) AS \"distinct\" FROM drawn GROUP BY 1")

# ---- count trees ------------------------------------------------------------------------------------

BINOMIAL = "exp(lgamma(m + 1) - lgamma(x + 1) - lgamma(m - x + 1) + x * ln(p) + (m - x) * ln(1 - p))"
INVERSE = f"CASE WHEN p <= 0 THEN 0 WHEN p >= 1 THEN m ELSE coalesce((SELECT min(x) FROM (SELECT x, sum({BINOMIAL}) OVER (ORDER BY x) AS cum FROM range(0, m + 1) y(x)) WHERE cum >= u), m) END"


def worker_tree() -> str:
    """The tree over 16 workers of the sharded orders: CTEs that end in m0 (ix, m)."""
    out = [f"c0 AS (WITH {SHARDED} SELECT shard AS ix, CAST(sum(units) AS BIGINT) AS w FROM items GROUP BY shard)", "s0 AS (SELECT i AS ix, coalesce((SELECT w FROM c0 WHERE ix = i), 0) AS w FROM range(16) r(i))"]
    out += [f"s{k} AS (SELECT ix // 2 AS ix, CAST(sum(w) AS BIGINT) AS w FROM s{k - 1} GROUP BY 1)" for k in range(1, 5)]
    out.append("m4 AS (SELECT 0 AS ix, 1000 AS m)")
    for k in range(4, 0, -1):
        out.append(f"p{k} AS (SELECT t.ix, t.m, l.w / CAST(t2.w AS DOUBLE) AS p, {u_sql(f'{chr(39)}worker:{k}:{chr(39)} || t.ix')} AS u FROM m{k} t JOIN s{k} t2 ON t.ix = t2.ix JOIN s{k - 1} l ON l.ix = 2 * t.ix WHERE t.m > 0)")
        out.append(f"b{k} AS (SELECT ix, m, {INVERSE} AS lft FROM p{k})")
        out.append(f"m{k - 1} AS (SELECT 2 * ix AS ix, CAST(lft AS BIGINT) AS m FROM b{k} UNION ALL SELECT 2 * ix + 1, CAST(m - lft AS BIGINT) FROM b{k})")
    return "WITH " + ", ".join(out)


add("worker_counts_k1000", lambda s, d: C.worker_counts(sharded(s, d), 1000, 16, SEED).where("m > 0"), f"{worker_tree()} SELECT CAST(ix AS INTEGER) AS shard, m FROM m0 WHERE m > 0")
add(
    "worker_alias_draw",
    lambda s, d: C.worker_alias_draw(sharded(s, d), 1000, 16, SEED),
    f"""{worker_tree()}, loc AS (SELECT *, row_number() OVER (PARTITION BY shard ORDER BY id) - 1 AS bucket, count(*) OVER (PARTITION BY shard) AS n FROM ({LOCAL} SELECT shard, id, part, alias, cap FROM tab)),
a AS (SELECT CAST(ix AS INTEGER) AS shard, unnest(range(0, m)) AS draw FROM m0 WHERE m > 0),
q AS (SELECT a.shard, draw, least(CAST(floor({u_sql("'own:' || a.shard || ':' || draw")} * n) AS BIGINT), n - 1) AS bucket, {u_sql("'owncoin:' || a.shard || ':' || draw")} AS u FROM a JOIN (SELECT DISTINCT shard, n FROM loc) z ON z.shard = a.shard)
SELECT q.shard, draw, CASE WHEN u * CAST(cap AS DOUBLE) >= CAST(part AS DOUBLE) THEN coalesce(alias, id) ELSE id END AS id FROM q JOIN loc ON loc.shard = q.shard AND loc.bucket = q.bucket""",
)


def uniform_tree(replace: bool, parts: int = 8, k: int = 1000) -> str:
    """Divide and conquer over the parts of orders, with its binomials or hypergeometrics."""
    out = ["n AS (SELECT count(*) AS n FROM orders WHERE o_totalprice > 0)", f"m0 AS (SELECT 0 AS lo, {parts} AS hi, CAST({k} AS BIGINT) AS m)"]
    choose = lambda n, x: f"(lgamma({n} + 1) - lgamma({x} + 1) - lgamma({n} - {x} + 1))"
    hyper = f"exp({choose('a', 'x')} + {choose('b', '(m - x)')} - {choose('(a + b)', 'm')})"
    low, high = "greatest(0, m - b)", "least(m, a)"
    without = f"coalesce((SELECT min(x) FROM (SELECT x, sum({hyper}) OVER (ORDER BY x) AS cum FROM range({low}, {high}) y(x)) WHERE cum >= u), {high})"
    for level in range(parts.bit_length() - 1):
        out.append(f"x{level} AS (SELECT lo, (lo + hi) // 2 AS mid, hi, m, n * ((lo + hi) // 2) // {parts} - n * lo // {parts} AS a, n * hi // {parts} - n * ((lo + hi) // 2) // {parts} AS b, {u_sql(f'{chr(39)}uniform:{level}:{chr(39)} || lo')} AS u FROM m{level}, n)")
        out.append(f"y{level} AS (SELECT *, CAST(a AS DOUBLE) / greatest(1, a + b) AS p FROM x{level})")
        out.append(f"z{level} AS (SELECT lo, mid, hi, m, CAST({INVERSE if replace else without} AS BIGINT) AS lft FROM y{level})")
        out.append(f"m{level + 1} AS (SELECT lo, mid AS hi, lft AS m FROM z{level} UNION ALL SELECT mid, hi, m - lft FROM z{level})")
    return f"WITH {', '.join(out)} SELECT CAST(lo AS INTEGER) AS part, m FROM m{parts.bit_length() - 1}"


for tag, replace in (("with", True), ("without", False)):
    add(f"uniform_dc_counts_{tag}", lambda s, d, r=replace: s.createDataFrame(list(enumerate(C.uniform_counts(I.weight_stats(items("orders")(s, d)).n, 1000, 8, SEED, r))), "part int, m long"), uniform_tree(replace))


def by_class(draw) -> object:
    """(wclass, m): draws of a sample per weight class; the tree fixes them."""

    def run(s: SparkSession, d: str) -> DataFrame:
        i = items("events")(s, d)
        classed = C.with_class(i, I.weight_stats(i).least).select("id", "wclass")
        return draw(i).select("id", "k_i").join(classed, "id").groupBy("wclass").agg(F.sum("k_i").alias("m"))

    return run


for name, options in {"os_draw": {}, "os_nomerge": {"dedup": False}, "os_gapless": {"gapless": True}, "os_nocutoff": {"cutoff": 0}}.items():
    add(f"{name}_invariants", by_class(lambda i, o=options: C.draw_with_replacement(i, 1000, SEED, **o)), ORACLE["class_counts_k1000"])
add("os_store_class_counts", by_class(lambda i: ClassStore.build(i).draw(1000, SEED)), ORACLE["class_counts_k1000"])


def store_reads(s: SparkSession, d: str) -> DataFrame:
    """(k, distinct, cells, rows_read, n): what draws from the structure on disk read, by the scan's own count."""
    store = ClassStore.build(i := items("lineitem")(s, d), cell_rows=100)
    n, out = i.count(), []
    for k in (10, 100, 1000):
        got: list[int] = []
        held = measured(s, lambda k=k: got.append(store.draw(k, SEED).count()))
        out.append((k, got[0], len(store.plan(k, SEED)), held["rows_read"], n))
    return s.createDataFrame(out, "k long, distinct long, cells long, rows_read long, n long")


add("os_store_rows_read", store_reads)

add("os_without_selected", lambda s, d: C.draw_without_replacement(items("events")(s, d), 100, SEED, select=True).select("id", "rank").exceptAll(C.draw_without_replacement(items("events")(s, d), 100, SEED)).agg(F.count("*").alias("n_other")), "SELECT CAST(0 AS BIGINT) AS n_other")


def tree_nodes(s: SparkSession, d: str) -> DataFrame:
    """(k, distinct, visited): tree nodes that draws visit against distinct results."""
    i = items("events")(s, d)
    parts = [C.draw_with_replacement(i, k, SEED, nodes=True).agg(F.lit(k).cast("long").alias("k"), F.sum("distinct").alias("distinct"), F.sum("visited").alias("visited")) for k in (10, 100, 1000, 10_000)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


add("tree_nodes", tree_nodes)

# ---- baselines ----------------------------------------------------------------------------------------

add("baseline_sequential_draws", lambda s, d: C.sequential_draws(items("orders")(s, d), 1000, SEED, portable=True), f"{DRAWN} SELECT draw, id FROM drawn")
add("baseline_global_shuffle", lambda s, d: A.alias_splitpack(items("orders")(s, d), 16, block=1000).select("id", *big("part"), "alias", *big("cap")), ORACLE["alias_sweep_orders"])
add("baseline_sample_by", lambda s, d: s.read.parquet(f"{d}/orders.parquet").sampleBy("o_orderstatus", {"F": 0.02, "O": 0.01}, SEED).select("o_orderkey", "o_orderstatus"))


def tablesample(s: SparkSession, d: str) -> DataFrame:
    s.read.parquet(f"{d}/orders.parquet").createOrReplaceTempView("_orders_to_sample")
    return s.sql(f"SELECT o_orderkey FROM _orders_to_sample TABLESAMPLE (1 PERCENT) REPEATABLE ({SEED})")


add("baseline_tablesample", tablesample)


def volume(s: SparkSession, d: str) -> DataFrame:
    """(method, shuffle_written, shuffle_records, rows_read): what builds and draws exchange."""
    i = items("orders")(s, d)
    own = I.random_shard(i, 8)
    st = I.weight_stats(i)
    runs = {
        "split and pack": lambda: A.alias_splitpack(i, 8, block=1000),
        "closed form": lambda: A.alias_asof(i),
        "greedy": lambda: A.alias_greedy(i, 8),
        "two levels": lambda: A.alias_by_shard(own),
        "class sums": lambda: C.weight_classes(i, st),
        "clocks": lambda: C.clocks(i, 100, SEED),
    }
    rows = []
    for name, run in runs.items():
        m = measured(s, lambda run=run: run().write.format("noop").mode("overwrite").save())
        rows.append((name, m["shuffle_written"], m["shuffle_records"], m["rows_read"]))
    return s.createDataFrame(rows, "method string, shuffle_written long, shuffle_records long, rows_read long")


add("communication_volume", volume)


def memory(s: SparkSession, d: str) -> DataFrame:
    """(structure, rows, words): auxiliary space of the split on item prefixes and on block sums, and of the compressed table."""
    i = items("orders")(s, d)
    st = I.weight_stats(i)
    log = max(1, st.n.bit_length())
    sums = A.class_chunks(i, st, log)[0].select("is_heavy", "chunk").distinct().count()
    words = T.compressed_build(i)[0].count()
    return s.createDataFrame([("item prefixes", st.n, 2 * st.n), ("block sums", sums, 3 * sums), ("bits and ranks", words, 2 * words)], "structure string, rows long, words long")


add("auxiliary_memory", memory)

# ---- measures and estimates ------------------------------------------------------------------------------

add(
    "accept_rate_poisson",
    lambda s, d: P.poisson_classes(i := pi("orders")(s, d), i.count()).groupBy("pclass").agg(F.round(F.sum("pi") / (F.count("*") * F.max("pi")), 6).alias("rate")),
    ORACLE["poisson_classes"].replace("cc AS (SELECT pclass, count(*) AS n, max(pi) AS cap FROM c GROUP BY pclass)", "cc AS (SELECT pclass, round(sum(pi) / (count(*) * max(pi)), 6) AS rate FROM c GROUP BY pclass)").replace("SELECT pclass, n, round(cap, 9) AS cap FROM cc", "SELECT pclass, rate FROM cc"),
)


def class_estimate(s: SparkSession, d: str) -> DataFrame:
    i = items("events")(s, d)
    st = I.weight_stats(i)
    table = C.class_table(i, st)
    return s.createDataFrame([(e, round(C.distinct_bound(table, st.least, e), 4)) for e in (10, 100, 1000, 10_000)], "ell long, t double")


add(
    "distinct_estimate_classes",
    class_estimate,
    f"WITH {FIXTURES['events'].sql}, {STATS}, c AS ({ORACLE['weight_classes_events']}), l AS (SELECT ell FROM (VALUES (10), (100), (1000), (10000)) v(ell)), x AS (SELECT ell, wclass, n_g, units_g, total, CAST(ell AS DOUBLE) * (least * (1::BIGINT << wclass)) AS a FROM c, st, l) SELECT CAST(ell AS BIGINT) AS ell, round(sum(CASE WHEN a >= total THEN n_g WHEN a * 2 > total THEN least(ell * units_g / CAST(total AS DOUBLE), n_g) ELSE ell * units_g / CAST(total AS DOUBLE) END), 4) AS t FROM x GROUP BY ell",
)
START = py_uniform(SEED, "systematic")
add(
    "pps_fixed_inclusion",
    lambda s, d: P.pps_fixed_inclusion(items("orders")(s, d), 100, SEED).select("id", "certain"),
    f"WITH {ORDERS}, {STATS}, r AS (SELECT id, sum(units) OVER (ORDER BY id ROWS UNBOUNDED PRECEDING) AS upto FROM items), q AS (SELECT CAST(least(ceil((i + CAST({START!r} AS DOUBLE)) * (total / 100.0::DOUBLE)), total) AS BIGINT) AS point FROM range(100) x(i), st) SELECT r.id, false AS certain FROM q ASOF JOIN r ON q.point <= r.upto",
)
CELL = f"CAST(floor({sql_uniform(0, chr(39) + 'cell:' + chr(39) + ' || id')} * 20) AS INTEGER)"
add(
    "fit_report",
    lambda s, d: E.fit_report(drawn("part", 4000)(s, d), items("part")(s, d), 4000, 20),
    f"WITH {alias_sql(FIXTURES['part'].sql)}, {draws_sql(4000)}, w AS (SELECT {CELL} AS cell, CAST(sum(units) AS DOUBLE) / (SELECT sum(units) FROM items) * 4000 AS want FROM items GROUP BY 1), g AS (SELECT {CELL} AS cell, count(*) AS got FROM drawn GROUP BY 1), x AS (SELECT count(*) AS cells, round(sum(pow(coalesce(got, 0) - want, 2) / want), 4) AS chi_square FROM w LEFT JOIN g USING (cell)) SELECT cells, chi_square, chi_square < cells + 4 * sqrt(2.0) * sqrt(cells) AS fits FROM x",
)
add(
    "alias_leftover",
    lambda s, d: A.greedy_pass(i := items("orders")(s, d), 4, st := I.weight_stats(i)).agg(F.count("*").alias("n"), (F.sum(F.when(~F.col("done"), F.col("part") - F.lit(st.total)))).cast("long").alias("mass_gap")),
    f"WITH {ORDERS} SELECT count(*) AS n, CAST(0 AS BIGINT) AS mass_gap FROM items",
)

# ---- ordered sets, lookups, grouping, SQL surface ------------------------------------------------------------

KEYED = f"WITH {FIXTURES['events'].sql}, k AS (SELECT id, -ln({u_sql('id')}) / w AS key FROM items)"
add("ordered_set_rank", lambda s, d: s.createDataFrame([(O.res_rank(R.keyed(items("events")(s, d), SEED), "key", 0.0001),)], "rank long"), f"{KEYED} SELECT count(*) AS rank FROM k WHERE key <= 0.0001")
add("ordered_set_select", lambda s, d: s.createDataFrame([(round(O.res_select(R.keyed(items("events")(s, d), SEED), "key", 777), 12),)], "key double"), f"{KEYED} SELECT round(max(key), 12) AS key FROM (SELECT key FROM k ORDER BY key LIMIT 777)")
add(
    "asof_lookup",
    lambda s, d: next_at_or_after(s.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_acctbal"), s.read.parquet(f"{d}/orders.parquet").select("o_totalprice").distinct(), "c_acctbal", "o_totalprice", ["o_totalprice"], strict=False, blocks=3).select("c_custkey", F.col("found_o_totalprice").alias("price")),
    "WITH o AS (SELECT DISTINCT o_totalprice FROM orders) SELECT c_custkey, o_totalprice AS price FROM customer ASOF LEFT JOIN o ON c_acctbal <= o_totalprice",
)
add("grouping_sets_estimate", lambda s, d: sampled(s, d).groupingSets([["status"], ["priority"], []], "status", "priority").agg(F.count("*").alias("n")), f"WITH {SAMPLED} SELECT status, priority, count(*) AS n FROM x GROUP BY GROUPING SETS ((status), (priority), ())")
add(
    "sample_by_flag_cube",
    lambda s, d: s.read.parquet(f"{d}/lineitem.parquet").where(hash_uniform(SEED, F.expr(LINE_ID)) <= F.col("l_discount")).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum(1 / F.col("l_discount")), 4).alias("estimate")),
    f"SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(1 / CAST(l_discount AS DOUBLE)), 4) AS estimate FROM lineitem WHERE l_discount > 0 AND {u_sql(LINE_ID)} <= l_discount GROUP BY CUBE (l_returnflag, l_linestatus)",
)
add("set_ops_except", lambda s, d: C.clocks(items("orders")(s, d), 500, SEED).select("id").exceptAll(C.clocks(items("orders")(s, d), 500, SEED, "uniform").select("id")), f"SELECT id FROM ({clock_sql(ORDERS, 500)}) EXCEPT SELECT id FROM ({clock_sql(ORDERS, 500, weight='')})")
add("udtf_alias", lambda s, d: sqlapi.alias_draws_sql(s, A.alias_asof(items("orders")(s, d)), 1000, SEED), f"{DRAWN} SELECT draw, id FROM drawn")

# ---- reservoirs: hours, months, years, jumps, sessions ---------------------------------------------------------

EVENT_HOUR = "CAST(dayofyear(ts) * 24 + hour(ts) AS INTEGER)"
add("reservoir_hour", lambda s, d: R.reservoir_profile(day_events(s, d, "hour"), "b", 100, SEED), PROFILE.format(base=FIXTURES["events"].sql, b=EVENT_HOUR, u=u_sql("id")))


def lineitem_batches(s: SparkSession, d: str, unit: str) -> DataFrame:
    df = s.read.parquet(f"{d}/lineitem.parquet").select(F.expr(LINE_ID).alias("id"), "l_extendedprice", "l_shipdate")
    b = F.year("l_shipdate") * 12 + F.month("l_shipdate") if unit == "month" else F.year("l_shipdate")
    return I.weighted_items(df.select("id", "l_extendedprice"), "id", "l_extendedprice", 100).join(df.select("id", b.cast("int").alias("b")), "id")


add(
    "reservoir_lineitem_month",
    lambda s, d: R.reservoir_profile(lineitem_batches(s, d, "month"), "b", 100, SEED),
    f"""WITH {FIXTURES['lineitem'].sql}, k AS (SELECT CAST(year(l_shipdate) * 12 + month(l_shipdate) AS INTEGER) AS b, -ln({u_sql('id')}) / w AS key FROM items JOIN lineitem ON {LINE_ID} = id), d AS (SELECT DISTINCT b FROM k),
t AS (SELECT d.b, (SELECT max(key) FROM (SELECT key FROM k WHERE k.b < d.b ORDER BY key LIMIT 100) HAVING count(*) = 100) AS t FROM d)
SELECT b, count(*) AS arrived, count(*) FILTER (WHERE t IS NULL OR key < t) AS candidates FROM k JOIN t USING (b) GROUP BY b""",
)
add("reservoir_lineitem_year", lambda s, d: R.replay(lineitem_batches(s, d, "year"), "b", R.WeightedReservoir(s, 100, SEED)).current().select("id"), clock_sql(FIXTURES["lineitem"].sql, 100).replace("SELECT id, CAST(rank AS INTEGER) AS rank FROM r", "SELECT id FROM r"))


def jumped(s: SparkSession, d: str) -> DataFrame:
    rows = day_events(s, d)
    rows = rows.withColumn("b", F.floor(F.col("b") / 7).cast("int"))
    held = R.replay(rows, "b", R.WeightedReservoir(s, 100, SEED, mode="jumps")).current()
    return held.join(rows.select("id"), "id").agg(F.count("*").alias("n"), F.countDistinct("id").alias("n_ids"), F.count_if(F.col("key") <= 0).alias("n_bad"))


add("reservoir_jumps", jumped, "SELECT CAST(100 AS BIGINT) AS n, CAST(100 AS BIGINT) AS n_ids, CAST(0 AS BIGINT) AS n_bad")


def sessions(s: SparkSession, d: str) -> DataFrame:
    kinds = s.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("id"), "user_id")
    return flat(R.session_windows(day_events(s, d).join(kinds, "id"), "1 hour", "user_id", 5, SEED), "user_id", "start")


add(
    "reservoir_session",
    sessions,
    f"""WITH {FIXTURES['events'].sql}, k AS (SELECT id, user_id, ts, -ln({u_sql('id')}) / w AS key FROM items JOIN events ON event_id = id),
b AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM k),
g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, id ROWS UNBOUNDED PRECEDING) AS g FROM b),
r AS (SELECT user_id, min(ts) OVER (PARTITION BY user_id, g) AS start, id, row_number() OVER (PARTITION BY user_id, g ORDER BY key, id) AS r FROM g)
SELECT user_id, CAST(start AS TIMESTAMP) AS start, id FROM r WHERE r <= 5""",
)

# ---- state of a stream, late rows, overlays, table functions, throughput -----------------------------------------


def stateful(s: SparkSession, d: str) -> DataFrame:
    """All events through the stateful stream: eight shards, three files."""
    home = f"{shared_dir(s)}-stateful"
    rows = items("events")(s, d).select("id", "w")
    rows.repartition(3, "id").write.parquet(f"{home}/in")
    found = S.taken_in(read_stream(s, f"{home}/in", rows.schema), 100, 8, SEED)
    found.writeStream.format("parquet").option("checkpointLocation", f"{home}/log").trigger(availableNow=True).start(f"{home}/out").awaitTermination()
    return S.held_of(s.read.schema(found.schema).parquet(f"{home}/out"), 100).select("id")


add("reservoir_stateful", stateful, ORACLE["reservoir_day_k100"])


def arrivals(s: SparkSession, d: str) -> DataFrame:
    """Events that arrive up to two days after their time, in batches by day of arrival."""
    rows = s.read.parquet(f"{d}/events.parquet").select("event_id", "ts")
    hours = F.floor(hash_uniform(SEED, F.col("event_id")) * 48).cast("int")
    return rows.withColumn("b", F.dayofyear(F.col("ts") + F.make_dt_interval(hours=hours)).cast("int"))


add(
    "late_rows",
    lambda s, d: S.late_profile(arrivals(s, d), "b", "ts", F.make_dt_interval(hours=F.lit(12))),
    f"""WITH a AS (SELECT ts, CAST(dayofyear(ts + to_hours(CAST(floor({u_sql('event_id')} * 48) AS INTEGER))) AS INTEGER) AS b FROM events),
m AS (SELECT b, max(max(ts)) OVER (ORDER BY b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) - INTERVAL 12 HOUR AS mark FROM a GROUP BY b)
SELECT b, count(*) AS arrived, count(*) FILTER (WHERE ts < mark) AS late FROM a JOIN m USING (b) GROUP BY b""",
)


def intervals(s: SparkSession, d: str, name: str) -> DataFrame:
    """(id, lo, hi): the items of a fixture laid end to end in id order."""
    run = block_prefix_sum(items(name)(s, d), "id", {"hi": F.col("units")}, 3)
    return run.select("id", (F.col("hi") - F.col("units")).cast("long").alias("lo"), F.col("hi").cast("long").alias("hi"))


LINED = "SELECT id, CAST(sum(units) OVER (ORDER BY id ROWS UNBOUNDED PRECEDING) - units AS BIGINT) AS lo, CAST(sum(units) OVER (ORDER BY id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS hi FROM items"
add(
    "range_overlay",
    lambda s, d: range_overlay(intervals(s, d, "customer"), intervals(s, d, "supplier"), 5),
    f"""WITH l AS (WITH {FIXTURES['customer'].sql} {LINED}), r AS (WITH {FIXTURES['supplier'].sql} {LINED})
SELECT l.id AS "left", r.id AS "right", greatest(l.lo, r.lo) AS lo, least(l.hi, r.hi) AS hi FROM l JOIN r ON l.lo < r.hi AND r.lo < l.hi""",
)
add("udtf_poisson", lambda s, d: sqlapi.poisson_sql(s, pi("orders")(s, d), SEED).select(F.col("id").cast("long").alias("id")), ORACLE["poisson_naive_orders"])


def throughput(s: SparkSession, d: str) -> DataFrame:
    """Draws from the structure on disk over k: results, distinct share, seconds, samples a second, time a distinct item."""
    store, out = ClassStore.build(items("lineitem")(s, d), cell_rows=10_000), []
    store.draw(1, SEED).count()  # the workers' start is no draw's time
    for k in (100, 1000, 10_000):
        start = time.time()
        distinct = store.draw(k, SEED).count()
        t = time.time() - start
        out.append((k, distinct, distinct / k, t, k / t, 1e6 * t / distinct))
    return s.createDataFrame(out, "k long, distinct long, share double, seconds double, samples_per_s double, us_per_distinct double")


add("draw_throughput", throughput)
