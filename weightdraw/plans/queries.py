"""The registry: one query per method, variant, baseline, measure and workload, with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.stored import materialise, shared_dir
from ..functions.variates import hash_uniform, sql_uniform
from ..operators import alias as A
from ..operators import classes as C
from ..operators import estimators as E
from ..operators import items as I
from ..operators import order as O
from ..operators import subset as P
from ..operators import tables as T
from ..operators.prefix import block_sums
from ..sources.tables import FIXTURES
from ..streaming import reservoir as R
from . import sqlapi

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}
SEED = 7


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLE[name] = sql


def items(name: str) -> Query:
    return lambda s, d: FIXTURES[name].items(s, d)


def big(*names: str) -> list:
    return [F.col(n).cast("long").alias(n) for n in names]


def one_row(spark: SparkSession, **values: int) -> DataFrame:
    return spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} long" for k in values))


# ---- SQL building blocks -------------------------------------------------------------------

STATS = "st AS (SELECT count(*) AS n, CAST(sum(units) AS BIGINT) AS total, min(units) AS least, max(units) AS most FROM items)"


def alias_sql(base: str, by: str = "") -> str:
    """CTEs of the sweep's closed form, ending in ``tab`` (shard?, id, part, alias, cap)."""
    part = f"PARTITION BY {by}" if by else ""
    own, eq = (f"{by}, ", f"l.{by} = h.{by} AND ") if by else ("", "")
    total = f"(SELECT CAST(sum(units) AS BIGINT) AS cap, count(*) AS n{', ' + by if by else ''} FROM items {'GROUP BY ' + by if by else ''})"
    on = f"USING ({by})" if by else "ON true"
    return f"""{base},
m AS (SELECT items.*, items.units * t.n AS mass, t.cap AS cap FROM items JOIN {total} t {on}),
light AS (SELECT {own}id, mass, cap, sum(cap - mass) OVER w - (cap - mass) AS d0, sum(cap - mass) OVER w AS d1, row_number() OVER w AS i, sum(mass) OVER w AS pl FROM m WHERE mass <= cap WINDOW w AS ({part} ORDER BY id ROWS UNBOUNDED PRECEDING)),
heavy AS (SELECT {own}id, mass, cap, sum(mass - cap) OVER w AS e, row_number() OVER w AS j, sum(mass) OVER w AS ph, lead(id) OVER ({part} ORDER BY id) AS nxt FROM m WHERE mass > cap WINDOW w AS ({part} ORDER BY id ROWS UNBOUNDED PRECEDING)),
tab AS (
  SELECT {'l.' + by + ', ' if by else ''}l.id, CAST(l.mass AS BIGINT) AS part, CASE WHEN l.mass < l.cap THEN h.id END AS alias, CAST(l.cap AS BIGINT) AS cap
  FROM light l ASOF LEFT JOIN heavy h ON {eq}l.d0 < h.e
  UNION ALL
  SELECT {'h.' + by + ', ' if by else ''}h.id, CAST(h.cap + h.e - coalesce(l.d1, h.e) AS BIGINT) AS part, CASE WHEN h.cap + h.e - coalesce(l.d1, h.e) < h.cap THEN h.nxt END AS alias, CAST(h.cap AS BIGINT) AS cap
  FROM heavy h ASOF LEFT JOIN light l ON {eq.replace('l.', 'x.').replace('h.', 'l.').replace('x.', 'h.')}h.e <= l.d1
)"""


def clock_sql(base: str, k: int | None, seed: int = SEED, weight: str = "w") -> str:
    key = f"-ln({sql_uniform(seed, 'CAST(id AS VARCHAR)')}) / {weight}" if weight else sql_uniform(seed, "CAST(id AS VARCHAR)")
    return f"WITH {base}, k AS (SELECT id, {key} AS key FROM items), r AS (SELECT id, row_number() OVER (ORDER BY key, id) AS rank FROM k) SELECT id, CAST(rank AS INTEGER) AS rank FROM r" + (f" WHERE rank <= {k}" if k else "")


def draws_sql(k: int, n: str = "(SELECT count(*) FROM tab)") -> str:
    return f"""q AS (SELECT i AS draw, least(CAST(floor({sql_uniform(SEED, "'bucket:' || i")} * {n}) AS BIGINT), {n} - 1) AS bucket, {sql_uniform(SEED, "'coin:' || i")} AS u FROM range({k}) r(i)),
b AS (SELECT *, row_number() OVER (ORDER BY id) - 1 AS bucket FROM tab),
drawn AS (SELECT draw, CASE WHEN u * CAST(cap AS DOUBLE) >= CAST(part AS DOUBLE) THEN coalesce(alias, id) ELSE id END AS id FROM q JOIN b USING (bucket))"""


def attempts_sql(k: int, tries: int, n: str) -> str:
    return f"a AS (SELECT d AS draw, t AS attempt, least(CAST(floor({sql_uniform(SEED, chr(39) + 'try:' + chr(39) + ' || d || ' + chr(39) + ':' + chr(39) + ' || t')} * {n}) AS BIGINT), {n} - 1) AS bucket, {sql_uniform(SEED, chr(39) + 'accept:' + chr(39) + ' || d || ' + chr(39) + ':' + chr(39) + ' || t')} AS u FROM range({k}) x(d), range({tries}) y(t))"


# ---- basics ---------------------------------------------------------------------------------

for name in ("orders", "events", "documents", "part", "customer", "lineitem"):
    base = FIXTURES[name].sql
    add(
        f"weight_stats_{name}",
        lambda s, d, f=name: FIXTURES[f].items(s, d).agg(F.count("*").alias("n"), F.sum("units").cast("long").alias("total"), F.min("units").cast("long").alias("least"), F.max("units").cast("long").alias("most")),
        f"WITH {base} SELECT count(*) AS n, CAST(sum(units) AS BIGINT) AS total, min(units) AS least, max(units) AS most FROM items",
    )
for name in ("orders", "events", "documents", "part"):
    base = FIXTURES[name].sql
    add(
        f"weight_classes_{name}",
        lambda s, d, f=name: C.weight_classes(FIXTURES[f].items(s, d)).select("wclass", "n_g", *big("units_g")),
        f"WITH {base}, {STATS}, r AS (SELECT units, least, CAST(floor(log2(CAST(units AS DOUBLE) / least)) AS INTEGER) AS r FROM items, st), c AS (SELECT units, CASE WHEN units < least * (1::BIGINT << r) THEN r - 1 WHEN units >= least * (1::BIGINT << (r + 1)) THEN r + 1 ELSE r END AS wclass FROM r) SELECT wclass, count(*) AS n_g, CAST(sum(units) AS BIGINT) AS units_g FROM c GROUP BY wclass",
    )
add("invalid_weights_customer", lambda s, d: I.count_invalid(s.read.parquet(f"{d}/customer.parquet"), "c_acctbal"), "SELECT count(*) AS n_rows, count(*) FILTER (WHERE c_acctbal IS NULL OR NOT c_acctbal > 0) AS n_invalid FROM customer")
add("classify_counts", lambda s, d: I.classify(items("orders")(s, d)).groupBy("is_heavy").agg(F.count("*").alias("n")), f"WITH {FIXTURES['orders'].sql}, {STATS} SELECT units * n > total AS is_heavy, count(*) AS n FROM (SELECT units, st.n, total FROM items, st) GROUP BY 1")


def prefix_light_heavy(s: SparkSession, d: str) -> DataFrame:
    """Running masses, a BIGINT as in the SQL while a class fits into one, DECIMAL(38,0) beyond."""
    i = items("orders")(s, d)
    st = I.weight_stats(i)
    whole = max((int(r["m"]) for r in I.classify(i, st).groupBy("is_heavy").agg(F.sum("mass").alias("m")).collect()), default=0)
    return A.ranked(i, st).select("id", "is_heavy", *(big("rank", "prefix") if whole < 1 << 63 else [*big("rank"), F.col("prefix")]))


add(
    "prefix_light_heavy",
    prefix_light_heavy,
    f"WITH {FIXTURES['orders'].sql}, {STATS}, m AS (SELECT id, units * n AS mass, units * n > total AS is_heavy FROM items, st) SELECT id, is_heavy, row_number() OVER w AS rank, CAST(sum(mass) OVER w AS BIGINT) AS prefix FROM m WINDOW w AS (PARTITION BY is_heavy ORDER BY id ROWS UNBOUNDED PRECEDING)",
)
add(
    "block_sums",
    lambda s, d: block_sums(items("orders")(s, d), "id", [4000, 8000, 12000], "units").select("block", "n", *big("total")),
    f"WITH {FIXTURES['orders'].sql} SELECT CAST(id >= 4000 AS INTEGER) + CAST(id >= 8000 AS INTEGER) + CAST(id >= 12000 AS INTEGER) AS block, count(*) AS n, CAST(sum(units) AS BIGINT) AS total FROM items GROUP BY 1",
)
add("hash_uniform_orders", lambda s, d: items("orders")(s, d).select("id", F.round(hash_uniform(SEED, F.col("id")), 9).alias("u")), f"WITH {FIXTURES['orders'].sql} SELECT id, round({sql_uniform(SEED, 'id')}, 9) AS u FROM items")

# ---- alias tables ---------------------------------------------------------------------------

TAB = "SELECT id, part, alias, cap FROM tab"
as_long = lambda t: t.select("id", "part", "alias", "cap").withColumns({c: F.col(c).cast("long") for c in ("part", "cap")})
for name in ("orders", "part", "events", "documents", "lineitem"):
    add(f"alias_asof_{name}", lambda s, d, f=name: as_long(A.alias_asof(items(f)(s, d))), f"WITH {alias_sql(FIXTURES[name].sql)} {TAB}")
ORDERS_TAB = f"WITH {alias_sql(FIXTURES['orders'].sql)} {TAB}"
add("alias_sweep_orders", lambda s, d: as_long(A.alias_sequential(items("orders")(s, d), "sweep")), ORDERS_TAB)
for p in (1, 4, 7):
    add(f"alias_splitpack_p{p}", lambda s, d, p=p: as_long(A.alias_splitpack(items("orders")(s, d), p, block=1000)), ORDERS_TAB)
add("alias_blockwise", lambda s, d: as_long(A.alias_blockwise(items("orders")(s, d), 4)), ORDERS_TAB)


def mass_summary(build: Callable[[DataFrame], DataFrame]) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        i = items("orders")(s, d)
        t = build(i)
        ok = A.mass_check(t, i, I.weight_stats(i)).agg(F.count("*").alias("n_items"), F.count_if("mass_ok").alias("n_mass_ok"))
        return ok.crossJoin(t.agg(F.count("*").alias("n_buckets")))

    return run


MASS = f"WITH {FIXTURES['orders'].sql} SELECT count(*) AS n_items, count(*) AS n_mass_ok, count(*) AS n_buckets FROM items"
add("alias_classic_mass", mass_summary(lambda i: A.alias_sequential(i, "classic")), MASS)
add("alias_greedy_mass", mass_summary(lambda i: A.alias_greedy(i, 4)), MASS)
add("alias_leftover_share", lambda s, d: A.greedy_pass(i := items("orders")(s, d), 4, I.weight_stats(i)).groupBy("done").agg(F.count("*").alias("n")))
add("alias_equal_weights", lambda s, d: as_long(A.alias_asof(I.weighted_items(s.read.parquet(f"{d}/part.parquet"), "p_partkey", F.lit(1.0)))), "SELECT p_partkey AS id, count(*) OVER () AS part, CAST(NULL AS BIGINT) AS alias, count(*) OVER () AS cap FROM part")


def split_query(p: int) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        i = items("orders")(s, d)
        st = I.weight_stats(i)
        return s.createDataFrame(A.split_states(A.ranked(i, st), st, [st.n * k // p for k in range(1, p)]), "n_prime long, light long, heavy long, spill long")

    return run


for p in (4, 7):
    cuts = f"(SELECT CAST(floor(CAST(n AS DOUBLE) * k / {p}) AS BIGINT) AS n_prime FROM (SELECT count(*) AS n FROM items), range(1, {p}) r(k))"
    add(
        f"split_states_p{p}",
        split_query(p),
        f"""WITH {alias_sql(FIXTURES['orders'].sql)},
c AS {cuts},
f AS (SELECT c.n_prime, coalesce(max(h.j), 0) AS heavy FROM c LEFT JOIN (SELECT h.j, h.ph FROM heavy h) h ON h.j <= c.n_prime AND h.ph + coalesce((SELECT l.pl FROM light l WHERE l.i = c.n_prime - h.j), 0) <= c.n_prime * (SELECT max(cap) FROM m) GROUP BY c.n_prime)
SELECT n_prime, n_prime - heavy AS light, heavy, CAST(coalesce((SELECT ph FROM heavy h WHERE h.j = f.heavy + 1), 0) + coalesce((SELECT pl FROM light l WHERE l.i = f.n_prime - f.heavy), 0) - n_prime * (SELECT max(cap) FROM m) AS BIGINT) AS spill FROM f""",
    )

# ---- draws ------------------------------------------------------------------------------------


def drawn(name: str, k: int, branchless: bool = False) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        i = items(name)(s, d)
        n = I.weight_stats(i).n
        return A.draw_alias(A.numbered(A.alias_asof(i), n), k, n, SEED, branchless)

    return run


DRAWN = f"WITH {alias_sql(FIXTURES['orders'].sql)}, {draws_sql(1000)}"
add("draw_alias_1000", drawn("orders", 1000), f"{DRAWN} SELECT draw, id FROM drawn")
add("draw_alias_branchless", drawn("orders", 1000, True), f"{DRAWN} SELECT draw, id FROM drawn")
add("draw_alias_counts", lambda s, d: A.draw_counts(drawn("orders", 1000)(s, d)), f"{DRAWN} SELECT id, count(*) AS k_i FROM drawn GROUP BY id")


def two_tables(s: SparkSession, d: str) -> DataFrame:
    i = items("orders")(s, d)
    n = I.weight_stats(i).n
    return A.draw_two_tables(*A.two_table_layout(A.numbered(A.alias_asof(i), n)), 1000, n, SEED)


add("draw_two_tables", two_tables, f"{DRAWN} SELECT draw, id FROM drawn")
FLAT = f"WITH {FIXTURES['part'].sql}, {STATS}, {attempts_sql(300, 12, '(SELECT n FROM st)')}, b AS (SELECT *, row_number() OVER (ORDER BY id) - 1 AS bucket FROM items), ok AS (SELECT draw, attempt, id FROM a JOIN b USING (bucket) WHERE u * (SELECT CAST(most AS DOUBLE) FROM st) <= units)"
add("draw_rejection_flat", lambda s, d: T.draw_rejection_flat(items("part")(s, d), 300, SEED), f"{FLAT} SELECT draw, arg_min(id, attempt) AS id, CAST(min(attempt) + 1 AS INTEGER) AS tries FROM ok GROUP BY draw")


def rej_sql(name: str) -> str:
    return f"""{FIXTURES[name].sql}, {STATS}, m AS (SELECT id, units * n AS mass, total AS cap, (units * n + total - 1) // total AS c FROM items, st), r AS (SELECT *, sum(c) OVER (ORDER BY id ROWS UNBOUNDED PRECEDING) - c AS c0 FROM m),
rt AS (SELECT CAST(c0 + j - 1 AS BIGINT) AS bucket, id, CAST(CASE WHEN j < c THEN cap ELSE mass - cap * (c - 1) END AS BIGINT) AS fill, cap FROM r, LATERAL (SELECT unnest(range(1, CAST(c AS BIGINT) + 1)) AS j))"""


REJ = rej_sql("orders")
add("rejection_table", lambda s, d: T.rejection_table(items("orders")(s, d)).select("bucket", "id", *big("fill", "cap")), f"WITH {REJ} SELECT bucket, id, fill, cap FROM rt")
REJ_DRAW = f"WITH {REJ}, {attempts_sql(300, 40, '(SELECT count(*) FROM rt)')}, ok AS (SELECT draw, attempt, id FROM a JOIN rt USING (bucket) WHERE u * CAST(cap AS DOUBLE) <= CAST(fill AS DOUBLE)) SELECT draw, arg_min(id, attempt) AS id FROM ok GROUP BY draw"


def rejection_draw(s: SparkSession, d: str) -> DataFrame:
    t = T.rejection_table(items("orders")(s, d))
    return T.draw_rejection(t, t.count(), 300, SEED)


def compressed(r: int) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        words, entries = T.compressed_build(items("orders")(s, d), r)
        return T.compressed_draw(words, entries, int(entries.agg(F.sum("c")).first()[0]), 300, SEED)

    return run


add("draw_rejection_table", rejection_draw, REJ_DRAW)
add("compressed_words", lambda s, d: T.compressed_build(items("orders")(s, d))[0], f"WITH {REJ}, w AS (SELECT CAST(c0 // 32 AS BIGINT) AS word_ix, CAST(sum(1::BIGINT << CAST(c0 % 32 AS INTEGER)) AS BIGINT) AS bits, count(*) AS ones FROM r GROUP BY 1) SELECT word_ix, bits, CAST(sum(ones) OVER (ORDER BY word_ix ROWS UNBOUNDED PRECEDING) - ones AS BIGINT) AS ones_before FROM w")
add("compressed_draw", compressed(1), REJ_DRAW)

# ---- two levels -------------------------------------------------------------------------------

SHARDED = "items AS (SELECT o_orderkey AS id, CAST(round(o_totalprice * 100) AS BIGINT) AS units, CAST(o_custkey % 16 AS INTEGER) AS shard FROM orders WHERE o_totalprice > 0)"


def sharded(s: SparkSession, d: str) -> DataFrame:
    df = s.read.parquet(f"{d}/orders.parquet").select("o_orderkey", "o_totalprice", "o_custkey")
    w = I.weighted_items(df, "o_orderkey", "o_totalprice", 100)
    return w.join(df.select(F.col("o_orderkey").alias("id"), (F.col("o_custkey") % 16).cast("int").alias("shard")), "id")


add("meta_weights", lambda s, d: T.meta_weights(sharded(s, d)).select("shard", "n_items", *big("units")), f"WITH {SHARDED} SELECT shard, count(*) AS n_items, CAST(sum(units) AS BIGINT) AS units FROM items GROUP BY shard")
META = f"WITH base AS (WITH {SHARDED} SELECT shard AS id, CAST(sum(units) AS BIGINT) AS units FROM items GROUP BY shard), {alias_sql('items AS (SELECT * FROM base)')}"
add("twolevel_top", lambda s, d: T.twolevel_build(sharded(s, d))[0].select("id", *big("part"), "alias", *big("cap")), f"{META} {TAB}")
LOCAL = f"WITH {alias_sql(SHARDED, 'shard')}"
for base in ("sweep",):
    add("twolevel_local", lambda s, d: A.alias_by_shard(sharded(s, d), "sweep").select("shard", "id", *big("part"), "alias", *big("cap")), f"{LOCAL} SELECT shard, id, part, alias, cap FROM tab")
add("twolevel_sqrt", lambda s, d: T.meta_weights(T.sqrt_shards(i := items("orders")(s, d), I.weight_stats(i).n)).select("shard", "n_items", *big("units")), f"WITH {FIXTURES['orders'].sql}, r AS (SELECT units, CAST((row_number() OVER (ORDER BY id) - 1) // CAST(floor(sqrt((SELECT count(*) FROM items))) AS BIGINT) AS INTEGER) AS shard FROM items) SELECT shard, count(*) AS n_items, CAST(sum(units) AS BIGINT) AS units FROM r GROUP BY shard")
add("twoalias_owner_mass", lambda s, d: T.twoalias_pieces(T.meta_weights(sharded(s, d))).groupBy(F.col("owner").alias("shard")).agg(F.sum("piece").cast("long").alias("mass")), f"WITH {SHARDED} SELECT shard, CAST(sum(units) * 16 AS BIGINT) AS mass FROM items GROUP BY shard")
add("load_profile", lambda s, d: T.load_profile(sharded(s, d), F.col("units")).select("shard", "items", *big("load")), f"WITH {SHARDED} SELECT shard, count(*) AS items, CAST(sum(units) AS BIGINT) AS load FROM items GROUP BY shard")

# ---- with replacement ---------------------------------------------------------------------------

CDF = f"WITH {FIXTURES['orders'].sql}, {STATS}, r AS (SELECT id, w, sum(units) OVER (ORDER BY id ROWS UNBOUNDED PRECEDING) AS upto FROM items), q AS (SELECT i AS draw, CAST(ceil({sql_uniform(SEED, chr(39) + 'cdf:' + chr(39) + ' || i')} * (SELECT CAST(total AS DOUBLE) FROM st)) AS BIGINT) AS point FROM range(1000) x(i)), drawn AS (SELECT draw, r.id FROM q ASOF JOIN r ON q.point <= r.upto)"
add("inverse_cdf_draw", lambda s, d: C.inverse_cdf_draw(items("orders")(s, d), 1000, SEED), f"{CDF} SELECT draw, id FROM drawn")


def os_workers(s: SparkSession, d: str) -> DataFrame:
    i = items("events")(s, d)
    got = C.draw_with_replacement(i, 1000, SEED, top="workers")
    return got.join(i.select("id"), "id").agg(F.sum("k_i").alias("k"), F.count_if(F.col("k_i") < 1).alias("n_bad"))


add("os_workers_invariants", os_workers, "SELECT CAST(1000 AS HUGEINT)::BIGINT AS k, 0 AS n_bad")


def class_counts(s: SparkSession, d: str) -> DataFrame:
    i = items("events")(s, d)
    st = I.weight_stats(i)
    held = {g: u for g, _, u in C.class_table(i, st)}
    counts = C.split_counts([held.get(g, 0) for g in range(16)], 1000, SEED)
    return s.createDataFrame([(g, m) for g, m in enumerate(counts) if m], "wclass int, m long")


def tree_sql() -> str:
    """The count tree over 16 padded leaves: one CTE a level, binomials by inverse CDF."""
    base = ORACLE["weight_classes_events"]
    out = [f"c0 AS ({base})", "s0 AS (SELECT i AS ix, coalesce((SELECT units_g FROM c0 WHERE wclass = i), 0) AS w FROM range(16) r(i))"]
    out += [f"s{k} AS (SELECT ix // 2 AS ix, CAST(sum(w) AS BIGINT) AS w FROM s{k - 1} GROUP BY 1)" for k in range(1, 5)]
    out.append("m4 AS (SELECT 0 AS ix, 1000 AS m)")
    for k in range(4, 0, -1):
        out.append(f"p{k} AS (SELECT t.ix, t.m, l.w / CAST(t2.w AS DOUBLE) AS p, {sql_uniform(SEED, chr(39) + f'node:{k}:' + chr(39) + ' || t.ix')} AS u FROM m{k} t JOIN s{k} t2 ON t.ix = t2.ix JOIN s{k - 1} l ON l.ix = 2 * t.ix WHERE t.m > 0)")
        term = "exp(lgamma(m + 1) - lgamma(x + 1) - lgamma(m - x + 1) + x * ln(p) + (m - x) * ln(1 - p))"
        out.append(f"b{k} AS (SELECT ix, m, CASE WHEN p <= 0 THEN 0 WHEN p >= 1 THEN m ELSE coalesce((SELECT min(x) FROM (SELECT x, sum({term}) OVER (ORDER BY x) AS cum FROM range(0, m + 1) y(x)) WHERE cum >= u), m) END AS lft FROM p{k})")
        out.append(f"m{k - 1} AS (SELECT 2 * ix AS ix, CAST(lft AS BIGINT) AS m FROM b{k} UNION ALL SELECT 2 * ix + 1, CAST(m - lft AS BIGINT) FROM b{k})")
    return "WITH " + ", ".join(out) + " SELECT CAST(ix AS INTEGER) AS wclass, m FROM m0 WHERE m > 0"


add("class_counts_k1000", class_counts, tree_sql())
KN = (0.001, 0.01, 0.1, 1.0)
SYNTH = {"uniform": (f"CAST(ceil({sql_uniform(SEED, 'id')} * 1048576) AS DOUBLE)", None), "p05": (None, 0.5), "p1": (None, 1.0), "p2": (None, 2.0)}
for tag, (_, power) in SYNTH.items():

    def ratio(s: SparkSession, d: str, power: float | None = power) -> DataFrame:
        rows = s.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("id"), hash_uniform(SEED, F.col("o_orderkey")).alias("u"))
        if power is None:
            w = rows.select("id", F.ceil(F.col("u") * 1048576).cast("double").alias("w"))
        else:
            n = rows.count()
            w = E.hash_rank(rows, n).select("id", F.pow("rank", F.lit(-power)).alias("w"))
        total = w.agg(F.sum("w")).first()[0]
        n = w.count()
        ks = [max(1, int(n * x)) for x in KN]
        p = F.col("w") / total
        agg = w.agg(*[F.round(F.sum(1 - F.exp(k * F.log1p(-p))) / k, 4).alias(f"k{k}") for k in ks]).first()
        return s.createDataFrame([(k, agg[f"k{k}"]) for k in ks], "k long, ratio double")

    w_sql = f"ceil({sql_uniform(SEED, 'o_orderkey')} * 1048576)" if power is None else f"pow(row_number() OVER (ORDER BY {sql_uniform(SEED, 'o_orderkey')}, o_orderkey), {-power})"
    add(f"distinct_ratio_{tag}", ratio, f"WITH x AS (SELECT CAST({w_sql} AS DOUBLE) AS w FROM orders), t AS (SELECT sum(w) AS total, count(*) AS n FROM x), k AS (SELECT greatest(1, CAST(floor(n * f) AS BIGINT)) AS k FROM t, (VALUES (CAST(0.001 AS DOUBLE)), (0.01), (0.1), (1.0)) v(f)) SELECT k, round(sum(1 - exp(k * ln(1 - w / total))) / k, 4) AS ratio FROM x, t, k GROUP BY k")
add("estimator_with", lambda s, d: E.estimate_total_with(A.draw_counts(C.inverse_cdf_draw(i := items("orders")(s, d), 1000, SEED)).join(i, "id"), I.weight_stats(i), F.lit(1.0)).select(F.round("estimate", 4).alias("estimate")), f"{CDF} SELECT round((SELECT total FROM st) / 1000.0 * sum(1.0 / units), 4) AS estimate FROM drawn JOIN items USING (id)")

# ---- without replacement ----------------------------------------------------------------------------

for name in ("orders", "events", "lineitem", "documents"):
    add(f"clocks_topk_{name}", lambda s, d, f=name: C.clocks(items(f)(s, d), 100, SEED), clock_sql(FIXTURES[name].sql, 100))
add("power_topk", lambda s, d: C.clocks(items("orders")(s, d).withColumn("w", F.col("w") / 1000), 100, SEED, "power"), clock_sql(FIXTURES["orders"].sql, 100))
add("uniform_topk", lambda s, d: C.clocks(items("part")(s, d), 100, SEED, "uniform"), clock_sql(FIXTURES["part"].sql, 100, weight=""))


def ell_query(name: str, ks: tuple[int, ...], how: str = "replicated") -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        i = items(name)(s, d)
        st = I.weight_stats(i)
        if how == "stepwise":
            return s.createDataFrame([(k, C.choose_ell_stepwise(i, st, k)) for k in ks], "k long, ell long")
        table = C.class_table(i, st)
        return s.createDataFrame([(k, C.choose_ell(table, st.least, k)) for k in ks], "k long, ell long")

    return run


def ell_sql(name: str, ks: tuple[int, ...]) -> str:
    e1 = "(exp(1) / (exp(1) - 1))"
    values = ", ".join(f"({k})" for k in ks)
    return f"""WITH {FIXTURES[name].sql}, {STATS}, c AS ({ORACLE[f'weight_classes_{name}']}),
g AS (SELECT wclass, n_g, units_g, coalesce(sum(units_g) OVER w, 0) AS hu, coalesce(sum(n_g) OVER w, 0) AS hc, lag(wclass) OVER (ORDER BY wclass) AS lighter, max(wclass) OVER () AS top FROM c WINDOW w AS (ORDER BY wclass ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
k AS (SELECT k, 2 * k * {e1} AS need FROM (VALUES {values}) v(k)),
cand AS (
  SELECT k, CAST(ceil(need) AS BIGINT) AS ell FROM k, st WHERE ceil(need) <= total / (2.0 * least * pow(2, (SELECT max(wclass) FROM g)))
  UNION ALL
  SELECT k, (total + (least * (1::BIGINT << wclass)) - 1) // (least * (1::BIGINT << wclass)) FROM k, st, g WHERE ((total + (least * (1::BIGINT << wclass)) - 1) // (least * (1::BIGINT << wclass))) * hu / CAST(total AS DOUBLE) + (n - hc) >= need
  UNION ALL
  SELECT k, CAST(ceil((need - (n - hc)) * total / hu) AS BIGINT) FROM k, st, g WHERE lighter IS NOT NULL AND hu > 0 AND ceil((need - (n - hc)) * total / hu) BETWEEN total / CAST(least * (1::BIGINT << wclass) AS DOUBLE) AND total / (2.0 * least * (1::BIGINT << lighter))
)
SELECT k, min(ell) AS ell FROM k LEFT JOIN cand USING (k) GROUP BY k"""


for name, ks in {"orders": (10, 100, 1500), "events": (10, 100, 1000), "documents": (10, 100), "part": (10, 100, 200)}.items():
    add(f"choose_ell_{name}", ell_query(name, ks), ell_sql(name, ks))
add("choose_ell_stepwise", ell_query("orders", (10, 100), "stepwise"), ell_sql("orders", (10, 100)))
add(
    "distinct_estimate",
    lambda s, d: E.distinct_estimate(items("orders")(s, d), [10, 100, 1000, 14483]),
    f"WITH {FIXTURES['orders'].sql}, {STATS}, l AS (SELECT ell FROM (VALUES (10), (100), (1000), (14483)) v(ell)) SELECT CAST(ell AS BIGINT) AS ell, round(sum(least(1.0, ell * units / CAST(total AS DOUBLE))), 4) AS t, round(sum(1 - exp(ell * ln(1 - units / CAST(total AS DOUBLE)))), 4) AS expected FROM items, st, l GROUP BY ell",
)
WITHOUT = lambda **o: (lambda s, d: C.draw_without_replacement(items("events")(s, d), 100, SEED, **o).agg(F.count("*").alias("n"), F.countDistinct("id").alias("n_ids"), F.max("rank").cast("long").alias("last")))
add("os_without_invariants", WITHOUT(), "SELECT 100 AS n, 100 AS n_ids, 100 AS last")
add("os_without_discard", WITHOUT(retry="discard"), "SELECT 100 AS n, 100 AS n_ids, 100 AS last")


def rejection_baseline(s: SparkSession, d: str) -> DataFrame:
    i = items("orders")(s, d)
    n = I.weight_stats(i).n
    return C.without_by_rejection(A.numbered(A.alias_asof(i), n), n, 100, SEED)


add("rejection_baseline", rejection_baseline, f"WITH {alias_sql(FIXTURES['orders'].sql)}, {draws_sql(1000)}, f AS (SELECT id, min(draw) AS draw FROM drawn GROUP BY id), r AS (SELECT id, row_number() OVER (ORDER BY draw) AS rank FROM f) SELECT id, CAST(rank AS INTEGER) AS rank FROM r WHERE rank <= 100")
add("estimator_without", lambda s, d: E.estimate_total_without(items("orders")(s, d), 100, SEED), f"WITH {FIXTURES['orders'].sql}, k AS (SELECT w, -ln({sql_uniform(SEED, 'id')}) / w AS key FROM items), r AS (SELECT *, row_number() OVER (ORDER BY key) AS r FROM k), t AS (SELECT key AS t FROM r WHERE r = 101) SELECT round(sum(w / (1 - exp(-w * t))), 2) AS estimate FROM r, t WHERE r <= 100")

# ---- permutation and selection ----------------------------------------------------------------------------

PERM = f"WITH {FIXTURES['orders'].sql}, k AS (SELECT id, -ln({sql_uniform(SEED, 'id')}) / w AS key FROM items) SELECT id, row_number() OVER (ORDER BY key, id) - 1 AS pos FROM k"
for how in ("sort", "bucketed"):
    add(f"permutation_{how}", lambda s, d, how=how: O.weighted_permutation(items("orders")(s, d), SEED, how, blocks=4), PERM)
add("permutation_occupancy", lambda s, d: O.bucket_occupancy(items("orders")(s, d), SEED).where("size > 0").agg(F.sum(F.col("size") * F.col("n_buckets")).alias("n"), F.max("size").alias("most")), f"WITH {FIXTURES['orders'].sql}, x AS (SELECT max(w) AS hi, count(*) AS n FROM items), k AS (SELECT greatest(-1, floor(n * ln((-ln({sql_uniform(SEED, 'id')}) / w) * n * hi))) AS ikey FROM items, x), c AS (SELECT count(*) AS size FROM k GROUP BY ikey) SELECT CAST(sum(size) AS BIGINT) AS n, max(size) AS most FROM c")


def stored_keys(s: SparkSession, d: str) -> DataFrame:
    return materialise(R.keyed(items("events")(s, d), SEED).select("key"))


def selected(pivots: int) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        keys = stored_keys(s, d)
        v, _ = O.select_threshold(keys, "key", 1000, pivots, finish=100, stored=True)
        return keys.where(F.col("key") <= v).agg(F.count("*").alias("rank"), F.round(F.max("key"), 9).alias("key"))

    return run


SELECTED = f"WITH {FIXTURES['events'].sql}, k AS (SELECT -ln({sql_uniform(SEED, 'id')}) / w AS key FROM items ORDER BY 1 LIMIT 1000) SELECT count(*) AS rank, round(max(key), 9) AS key FROM k"
add("select_1pivot", selected(1), SELECTED)
add("select_8pivots", selected(8), SELECTED)
add("select_unsorted", lambda s, d: O.smallest(R.keyed(items("events")(s, d), SEED), "key", 1000).agg(F.count("*").alias("rank"), F.round(F.max("key"), 9).alias("key")), SELECTED)
add("select_range", lambda s, d: one_row(s, ok=int(900 <= O.select_range(R.keyed(items("events")(s, d), SEED), "key", 900, 1100)[1] <= 1100)), "SELECT CAST(1 AS BIGINT) AS ok")
add("ordered_set_split", lambda s, d: O.res_split(R.keyed(items("events")(s, d), SEED), "key", 0.0001)[0].select("id"), f"WITH {FIXTURES['events'].sql} SELECT id FROM items WHERE -ln({sql_uniform(SEED, 'id')}) / w <= 0.0001")


def selection_rounds(s: SparkSession, d: str) -> DataFrame:
    keys = stored_keys(s, d)
    return s.createDataFrame([(p, k, O.select_threshold(keys, "key", k, p, finish=100, stored=True)[1]) for p in (1, 8) for k in (100, 1000)], "pivots int, k long, rounds int")


add("selection_rounds", selection_rounds)

# ---- subsets ------------------------------------------------------------------------------------------------

PI = {
    "lineitem": ("lineitem", FIXTURES["lineitem"].id_sql, "l_discount"),
    "orders": ("orders", "o_orderkey", "least(1.0, o_totalprice / 1500000)"),
    "labels": ("labels", "doc_id", "quality"),
}


def pi(name: str) -> Query:
    t, i, p = PI[name]
    return lambda s, d: P.inclusion_items(s.read.parquet(f"{d}/{t}.parquet"), F.expr(i), F.expr(p))


def pi_sql(name: str) -> str:
    t, i, p = PI[name]
    return f"items AS (SELECT {i} AS id, CAST({p} AS DOUBLE) AS pi FROM {t} WHERE {p} > 0)"


for name in PI:
    add(f"poisson_naive_{name}", lambda s, d, f=name: P.poisson_naive(pi(f)(s, d), SEED), f"WITH {pi_sql(name)} SELECT id FROM items WHERE {sql_uniform(SEED, 'CAST(id AS VARCHAR)')} <= pi")
PCLASS = f"WITH {pi_sql('orders')}, x AS (SELECT greatest(1, CAST(ceil(log2(count(*))) AS INTEGER)) AS top FROM items), r AS (SELECT id, pi, CAST(floor(-log2(pi)) AS INTEGER) AS r, top FROM items, x), c AS (SELECT id, pi, least(CASE WHEN pow(2.0, -r) < pi THEN r - 1 WHEN pow(2.0, -(r + 1)) >= pi THEN r + 1 ELSE r END, top) AS pclass FROM r), cc AS (SELECT pclass, count(*) AS n, max(pi) AS cap FROM c GROUP BY pclass)"
add("poisson_classes", lambda s, d: P.poisson_classes(i := pi("orders")(s, d), i.count()).groupBy("pclass").agg(F.count("*").alias("n"), F.round(F.max("pi"), 9).alias("cap")), f"{PCLASS} SELECT pclass, n, round(cap, 9) AS cap FROM cc")
add(
    "poisson_skips",
    lambda s, d: P.poisson_sample(pi("orders")(s, d), SEED),
    f"""{PCLASS}, tt AS (SELECT pclass, n, cap, unnest(range(1, CAST(2 * n * cap + 300 AS BIGINT))) AS t FROM cc),
g AS (SELECT pclass, n, cap, t, 1 + CASE WHEN cap >= 1 THEN 0 ELSE floor(ln({sql_uniform(SEED, "'skip:' || pclass || ':0:' || t")}) / ln(1 - cap)) END AS gap FROM tt),
h AS (SELECT pclass, n, cap, t, sum(gap) OVER (PARTITION BY pclass ORDER BY t ROWS UNBOUNDED PRECEDING) - 1 AS pos FROM g),
dd AS (SELECT id, pi, pclass, row_number() OVER (PARTITION BY pclass ORDER BY id) - 1 AS pos FROM c)
SELECT id FROM dd JOIN h USING (pclass, pos) WHERE {sql_uniform(SEED, "'acc:' || pclass || ':0:' || t")} * h.cap <= pi""",
)
add(
    "bernoulli_skips",
    lambda s, d: P.bernoulli_items(items("orders")(s, d), 0.05, SEED).select("id"),
    f"WITH {FIXTURES['orders'].sql}, n AS (SELECT count(*) AS n FROM items), t AS (SELECT unnest(range(1, CAST(n // 8 + 300 AS BIGINT))) AS t FROM n), g AS (SELECT t, 1 + floor(ln({sql_uniform(SEED, chr(39) + 'bernoulli:0:0:' + chr(39) + ' || t')}) / ln(1 - CAST(0.05 AS DOUBLE))) AS gap FROM t), h AS (SELECT CAST(sum(gap) OVER (ORDER BY t ROWS UNBOUNDED PRECEDING) - 1 AS BIGINT) AS pos FROM g), dd AS (SELECT id, row_number() OVER (ORDER BY id) - 1 AS pos FROM items) SELECT id FROM dd JOIN h USING (pos)",
)
add("poisson_assign", lambda s, d: P.poisson_assign(pi("orders")(s, d), 8).groupBy("worker").agg(F.count("*").alias("n")), f"WITH {pi_sql('orders')}, u AS (SELECT id, CAST(round(pi * 1000000) AS BIGINT) AS u FROM items), r AS (SELECT u, sum(u) OVER (ORDER BY id ROWS UNBOUNDED PRECEDING) - u AS before, (SELECT sum(u) FROM u) AS total FROM u) SELECT CAST(least(7, floor(before * 8 / total)) AS INTEGER) AS worker, count(*) AS n FROM r GROUP BY 1")
add("poisson_compact", lambda s, d: P.compact(P.poisson_naive(pi("orders")(s, d), SEED)), f"WITH {pi_sql('orders')}, x AS (SELECT id FROM items WHERE {sql_uniform(SEED, 'id')} <= pi) SELECT id, row_number() OVER (ORDER BY id) - 1 AS pos FROM x")


def per_shard(s: SparkSession, d: str) -> DataFrame:
    i = pi("orders")(s, d).withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(8)).cast("int"))
    got = P.poisson_per_shard(i, SEED)
    return got.agg((F.count("*") - F.countDistinct("id")).alias("n_repeats")).crossJoin(got.join(i, "id", "left_anti").agg(F.count("*").alias("n_foreign")))


add("poisson_per_shard", per_shard, "SELECT 0 AS n_repeats, 0 AS n_foreign")
add("estimator_poisson", lambda s, d: E.estimate_total_poisson(P.poisson_naive(i := pi("orders")(s, d), SEED).join(i, "id"), F.lit(1.0)), f"WITH {pi_sql('orders')} SELECT round(sum(1 / pi), 4) AS estimate FROM items WHERE {sql_uniform(SEED, 'id')} <= pi")

# ---- reservoirs ------------------------------------------------------------------------------------------------


def day_events(s: SparkSession, d: str, unit: str = "day") -> DataFrame:
    df = s.read.parquet(f"{d}/events.parquet").select("event_id", "value", "ts")
    w = I.weighted_items(df, "event_id", "value", 100)
    b = F.dayofyear("ts") if unit == "day" else (F.dayofyear("ts") * 24 + F.hour("ts"))
    return w.join(df.select(F.col("event_id").alias("id"), b.cast("int").alias("b"), "ts"), "id")


def reservoir(k: int, days: int = 1, **options: object) -> Query:
    """Replay of all events in batches of ``days`` days."""

    def run(s: SparkSession, d: str) -> DataFrame:
        rows = day_events(s, d)
        rows = rows.withColumn("b", F.floor(F.col("b") / days).cast("int"))
        return R.replay(rows, "b", R.WeightedReservoir(s, k, SEED, **options)).current().select("id")

    return run


add("reservoir_day_k100", reservoir(100), clock_sql(FIXTURES["events"].sql, 100).replace("SELECT id, CAST(rank AS INTEGER) AS rank FROM r", "SELECT id FROM r"))
for k in (10, 1000):
    add(f"reservoir_week_k{k}", reservoir(k, 7), ORACLE["reservoir_day_k100"].replace("rank <= 100", f"rank <= {k}"))
for tag, options in {"reservoir_1pivot": {"pivots": 1, "finish": 0}, "reservoir_8pivots": {"pivots": 8, "finish": 0}, "reservoir_gather": {"mode": "gather"}}.items():
    add(tag, reservoir(100, 7, **options), ORACLE["reservoir_day_k100"])
add("reservoir_uniform", reservoir(100, 7, weighted=False), clock_sql(FIXTURES["events"].sql, 100, weight="").replace("SELECT id, CAST(rank AS INTEGER) AS rank FROM r", "SELECT id FROM r"))
PROFILE = """WITH {base}, k AS (SELECT {b} AS b, -ln({u}) / w AS key FROM items JOIN events ON event_id = id), d AS (SELECT DISTINCT b FROM k),
t AS (SELECT d.b, (SELECT max(key) FROM (SELECT key FROM k WHERE k.b < d.b ORDER BY key LIMIT 100) HAVING count(*) = 100) AS t FROM d)
SELECT b, count(*) AS arrived, count(*) FILTER (WHERE t IS NULL OR key < t) AS candidates FROM k JOIN t USING (b) GROUP BY b"""
add("reservoir_profile", lambda s, d: R.reservoir_profile(day_events(s, d), "b", 100, SEED), PROFILE.format(base=FIXTURES["events"].sql, b="CAST(dayofyear(ts) AS INTEGER)", u=sql_uniform(SEED, "id")))
GROUPED = "WITH {base}, k AS (SELECT id, {g}, -ln({u}) / w AS key FROM items JOIN events ON event_id = id{x}), r AS (SELECT *, row_number() OVER (PARTITION BY {p} ORDER BY key, id) AS r FROM k) SELECT {p}, id FROM r WHERE r <= 5"
flat = lambda df, *keys: df.select(*keys, F.explode("ids").alias("id"))
add("topk_by_type", lambda s, d: flat(R.bottom_k(items("events")(s, d).join(s.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("id"), "event_type"), "id"), {"event_type": F.col("event_type")}, 5, SEED), "event_type"), GROUPED.format(base=FIXTURES["events"].sql, g="event_type", u=sql_uniform(SEED, "id"), x="", p="event_type"))
add("reservoir_window_tumbling", lambda s, d: flat(R.windowed(day_events(s, d), "1 day", 5), "start"), GROUPED.format(base=FIXTURES["events"].sql, g="CAST(date_trunc('day', ts) AS TIMESTAMP) AS start", u=sql_uniform(SEED, "id"), x="", p="start"))
add("reservoir_window_sliding", lambda s, d: flat(R.windowed(day_events(s, d), "1 day", 5, slide="6 hours"), "start"), GROUPED.format(base=FIXTURES["events"].sql, g="CAST(time_bucket(INTERVAL 6 HOURS, ts) - INTERVAL 6 HOURS * j AS TIMESTAMP) AS start", u=sql_uniform(SEED, "id"), x=", range(4) y(j)", p="start"))

# ---- surrounding operators -------------------------------------------------------------------------------------------

TOP = clock_sql(FIXTURES["orders"].sql, 100)
orders = lambda s, d: s.read.parquet(f"{d}/orders.parquet")
add("semi_join_payload", lambda s, d: orders(s, d).join(F.broadcast(C.clocks(items("orders")(s, d), 100, SEED).withColumnRenamed("id", "o_orderkey")), "o_orderkey", "left_semi").select("o_orderkey", "o_orderstatus", "o_totalprice"), f"SELECT o_orderkey, o_orderstatus, o_totalprice FROM orders WHERE o_orderkey IN (SELECT id FROM ({TOP}))")
add("anti_join_complement", lambda s, d: orders(s, d).join(F.broadcast(C.clocks(items("orders")(s, d), 100, SEED).withColumnRenamed("id", "o_orderkey")), "o_orderkey", "left_anti").agg(F.count("*").alias("n")), f"SELECT count(*) AS n FROM orders WHERE o_orderkey NOT IN (SELECT id FROM ({TOP}))")
add("json_weight", lambda s, d: C.clocks(I.weighted_items(s.read.parquet(f"{d}/events.parquet"), "event_id", F.get_json_object("props", "$.k")), 50, SEED), clock_sql("items AS (SELECT event_id AS id, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS w FROM events WHERE CAST(json_extract_string(props, '$.k') AS DOUBLE) > 0)", 50))
add("array_norm_weight", lambda s, d: C.clocks(I.weighted_items(s.read.parquet(f"{d}/embeddings.parquet"), "vec_id", F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 1_000_000), 50, SEED), clock_sql("items AS (SELECT vec_id AS id, sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))) AS w FROM embeddings)", 50))
add("dimension_weight_nation", lambda s, d: C.clocks(I.weighted_items(s.read.parquet(f"{d}/customer.parquet").groupBy("c_nationkey").count(), "c_nationkey", "count"), 10, SEED), clock_sql("items AS (SELECT c_nationkey AS id, CAST(count(*) AS DOUBLE) AS w FROM customer GROUP BY 1)", 10))
SAMPLED = f"s AS ({TOP}), x AS (SELECT o_orderstatus AS status, o_orderpriority AS priority FROM orders JOIN s ON o_orderkey = id)"


def sampled(s: SparkSession, d: str) -> DataFrame:
    top = C.clocks(items("orders")(s, d), 100, SEED).withColumnRenamed("id", "o_orderkey")
    return orders(s, d).join(F.broadcast(top), "o_orderkey").select(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"))


add("rollup_estimate", lambda s, d: sampled(s, d).rollup("status", "priority").agg(F.count("*").alias("n")), f"WITH {SAMPLED} SELECT status, priority, count(*) AS n FROM x GROUP BY ROLLUP (status, priority)")
add("cube_estimate", lambda s, d: sampled(s, d).cube("status", "priority").agg(F.count("*").alias("n")), f"WITH {SAMPLED} SELECT status, priority, count(*) AS n FROM x GROUP BY CUBE (status, priority)")
add("set_ops_overlap", lambda s, d: C.clocks(items("orders")(s, d), 500, SEED).select("id").intersect(C.clocks(items("orders")(s, d), 500, SEED, "uniform").select("id")), f"SELECT id FROM ({clock_sql(FIXTURES['orders'].sql, 500)}) INTERSECT SELECT id FROM ({clock_sql(FIXTURES['orders'].sql, 500, weight='')})")
add("stratified_by_nation", lambda s, d: flat(R.bottom_k(I.weighted_items(c := s.read.parquet(f"{d}/customer.parquet"), "c_custkey", "c_acctbal", 100).join(c.select(F.col("c_custkey").alias("id"), "c_nationkey"), "id"), {"c_nationkey": F.col("c_nationkey")}, 3, SEED), "c_nationkey"), f"WITH k AS (SELECT c_custkey AS id, c_nationkey, -ln({sql_uniform(SEED, 'c_custkey')}) / c_acctbal AS key FROM customer WHERE c_acctbal > 0), r AS (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY key, id) AS r FROM k) SELECT c_nationkey, id FROM r WHERE r <= 3")
add("baseline_spark_sample", lambda s, d: orders(s, d).sample(fraction=0.01, seed=SEED).select("o_orderkey"))
add("window_key_ranks", lambda s, d: items("events")(s, d).join(s.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("id"), "event_type"), "id").select("id", F.ntile(4).over(Window.partitionBy("event_type").orderBy("w", "id")).alias("quarter")), f"WITH {FIXTURES['events'].sql} SELECT id, CAST(ntile(4) OVER (PARTITION BY event_type ORDER BY w, id) AS INTEGER) AS quarter FROM items JOIN events ON event_id = id")


def udtf_sample(s: SparkSession, d: str) -> DataFrame:
    kinds = s.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("id"), F.col("event_type").alias("grp"))
    return sqlapi.sample_by_group_sql(s, items("events")(s, d).join(kinds, "id"), 5, SEED).select(F.col("grp").alias("event_type"), "id")


add("udtf_weighted_sample", udtf_sample, ORACLE["topk_by_type"])
add("map_of_counts", lambda s, d: A.draw_counts(drawn("orders", 1000)(s, d)).agg(F.map_from_entries(F.collect_list(F.struct("id", "k_i"))).alias("m")).select(F.size("m").cast("long").alias("n_ids"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("k")), f"{DRAWN} SELECT count(DISTINCT id) AS n_ids, count(*) AS k FROM drawn")


def streamed(s: SparkSession, d: str) -> DataFrame:
    """The reservoir fed by Structured Streaming from files of the events table."""
    from ..sources.tables import read_stream

    home = f"{shared_dir(s)}-stream"
    rows = items("events")(s, d).select("id", "w")
    rows.repartition(3, "id").write.parquet(f"{home}/in")
    held = R.WeightedReservoir(s, 100, SEED, path=f"{home}/state")
    R.stream_into(held, read_stream(s, f"{home}/in", rows.schema), f"{home}/log").awaitTermination()
    return held.current().select("id")


add("reservoir_streamed", streamed, ORACLE["reservoir_day_k100"])

from . import more  # noqa: E402, F401 - registers the rest
