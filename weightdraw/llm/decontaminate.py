"""Benchmark decontamination by template canonicalisation (operator 5, native).

Built-in functions only: no Python runs on the executors.

* Tokens are words and numbers.  In a template, numbers, units and names (capitalised
  words inside a sentence) become typed placeholders, other words are lower-cased.
  Items and documents are taken as templates and, where that differs, in plain lower
  case, so a verbatim copy or one with changed case matches whatever it holds.
* Windows of WINDOW tokens (or the whole item, if shorter) are hashed; templates that are
  mostly placeholders say nothing and are left out, plain windows never are.  The first
  word of an item is also indexed as the name it looks like inside a document's sentence.
  One scan of the documents hashes every window of every whole text and hash-joins the
  item windows, which are sent out when their counted size allows it and joined by a
  shuffle otherwise.
* Matches of one document and item at one offset form a chain.  In a chain that covers
  placeholders the values must correspond one to one (the same value in the item always
  stands for the same value in the document, and the reverse): a re-parameterised
  question keeps that, a chance meeting of templates does not.  Plain windows that hold
  values are judged with all windows of their chain, whose other words must be equal.
* A document is contaminated by an item when its consistent chains cover at least
  MATCHED tokens of it, or the whole item if it is shorter.

Defined results for odd rows: null and empty texts are clean; items that are null or
have fewer than SHORTEST tokens never match; repeated documents are judged each, rows
that share a doc_id share the verdict, null doc_ids count as one id; an empty table, of
documents or of items, gives clean documents or no rows.  Extra columns are kept by
``clean`` and ignored by ``contamination``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, ship, unused

WINDOW, MATCHED, SHORTEST = 8, 13, 4
#: Item windows (16 bytes each and overhead) or chains that may be broadcast.
BROADCAST_ROWS = 500_000
#: Unit words: fixed values.
UNITS = (
    "mm cm m km inch inches foot feet yard yards mile miles mg g gram grams kg kilogram kilograms ton tons ounce ounces pound pounds "
    "ml l litre litres liter liters gallon gallons second seconds minute minutes hour hours day days week weeks month months year years "
    "dollar dollars cent cents euro euros percent degree degrees watt watts volt volts"
).split()
SLOT = "§"


def tokens(text: Column) -> Column:
    """Words and numbers in order; a word that looks like a name carries the slot mark."""
    marked = F.regexp_replace(F.coalesce(text, F.lit("")), r"(?<=[\p{Ll}\p{N},;:] )(?=\p{Lu}\p{Ll})", SLOT)
    return F.regexp_extract_all(marked, F.lit(rf"{SLOT}?\p{{L}}[\p{{L}}\p{{M}}]*|\p{{N}}+(?:[.,]\p{{N}}+)*"), F.lit(0))


def template(token: Column) -> Column:
    """The token of a template: a typed placeholder or the lower-cased word."""
    low = F.lower(token)
    first = F.substring(token, 1, 1)
    return F.when(first == SLOT, SLOT + "name").when(first.between("0", "9"), SLOT + "number").when(low.isin(UNITS), SLOT + "unit").otherwise(low)


def plain(token: Column) -> Column:
    return F.lower(F.ltrim(token, F.lit(SLOT)))


def _windows(hashes: Column, size: Column | int) -> Column:
    """Hash of each run of ``size`` token hashes."""
    size = F.lit(size) if isinstance(size, int) else size
    n = F.size(hashes)
    starts = F.when(n >= size, F.sequence(F.lit(1), n - size + 1)).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda i: F.xxhash64(F.slice(hashes, i, size)))


def item_windows(benchmark: DataFrame) -> DataFrame:
    """(hash, size, item_id, form, ipos, slots) of the indexed windows.

    Form 0 is the template, 1 the plain form without values; form 2, judged with its
    whole chain, is the plain form with values, or a template whose first word is
    marked as a name.
    """
    items = benchmark.select("item_id", tokens(F.col("text").cast("string")).alias("raw")).where(F.size("raw") >= SHORTEST)
    items = items.withColumn("kinds", F.transform("raw", template))
    shape = lambda rows, form, t: rows.select("item_id", F.lit(form).alias("form"), t.alias("t"), "kinds")
    start = F.concat(F.array(F.lit(SLOT + "name")), F.expr("slice(kinds, 2, size(kinds))"))
    forms = shape(items, 0, F.col("kinds")).unionByName(shape(items, 1, F.transform("raw", plain)))
    forms = forms.unionByName(shape(items.where(F.get("raw", F.lit(0)).rlike(r"^\p{Lu}\p{Ll}")), 2, start))
    size = F.least(F.size("t"), F.lit(WINDOW))
    cut = forms.select("item_id", "form", size.alias("size"), "kinds", F.posexplode(_windows(F.transform("t", lambda x: F.xxhash64(x)), size)).alias("ipos", "hash"))
    count = lambda test: F.size(F.filter(F.expr("slice(kinds, ipos + 1, size)"), test))
    cut = cut.withColumn("slots", count(lambda x: F.substring(x, 1, 1) == SLOT)).withColumn("values", count(lambda x: x.isin(SLOT + "number", SLOT + "unit")))
    found = cut.where("form = 1 or slots * 8 <= size * 3 and (form = 0 or ipos = 0)")
    found = found.withColumn("slots", F.when(F.col("form") == 1, 0).otherwise(F.col("slots"))).withColumn("form", F.when((F.col("form") == 1) & (F.col("values") > 0), 2).otherwise(F.col("form")))
    # a plain window equal to the template's is the same window
    return found.groupBy("hash", "size", "item_id", "ipos").agg(F.min("form").alias("form"), F.max("slots").alias("slots"))


def contamination(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, matched (tokens), n_tokens, reparameterised: one row per contaminated pair."""
    spark = docs.sparkSession
    index = materialise(item_windows(benchmark))
    n = index.count()
    sizes = sorted(r["size"] for r in index.select("size").distinct().collect())  # at most WINDOW values
    if not n:
        return spark.createDataFrame([], "doc_id long, item_id long, matched long, n_tokens int, reparameterised boolean")
    index = F.broadcast(index) if n <= BROADCAST_ROWS else index
    texts = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    raw = texts.select("doc_id", tokens(F.col("text")).alias("raw"))
    hashed = raw.select("doc_id", F.transform("raw", lambda t: F.xxhash64(template(t))).alias("h"), F.transform("raw", lambda t: F.xxhash64(plain(t))).alias("g"))
    hits = None
    for size in sizes:
        both = F.concat(_windows(F.col("h"), size), _windows(F.col("g"), size))
        windows = hashed.select("doc_id", (F.size("h") - size + 1).alias("n"), F.posexplode(both).alias("at", "hash"))
        windows = windows.select("doc_id", F.expr("if(at < n, at, at - n)").alias("dpos"), "hash")
        part = windows.join(index.where(F.col("size") == size), "hash")
        hits = part if hits is None else hits.unionByName(part)
    # hashes of the two forms are equal only without slots, so either may meet either
    chains = hits.groupBy("doc_id", "item_id", "form", (F.col("dpos") - F.col("ipos")).alias("shift")).agg(F.collect_set(F.struct("ipos", "size")).alias("at"), F.max("slots").alias("slots"))
    chains = materialise(chains)
    # form 2 takes in its chain's other windows and is always compared by its values
    wide = chains.groupBy("doc_id", "item_id", "shift").agg(F.max("form").alias("form"), F.flatten(F.collect_set("at")).alias("at"), F.lit(1).alias("slots")).where("form = 2")
    chains = chains.where("form < 2").unionByName(wide)
    covered = F.array_distinct(F.flatten(F.transform("at", lambda a: F.sequence(a["ipos"], a["ipos"] + a["size"] - 1))))
    chains = materialise(chains.select("doc_id", "item_id", "form", "shift", covered.alias("covered"), "slots"))
    items = benchmark.select("item_id", tokens(F.col("text").cast("string")).alias("raw")).dropDuplicates(["item_id"])
    literal = chains.where("slots = 0").select("doc_id", "item_id", "covered", F.lit(False).alias("changed"))
    valued = chains.where("slots > 0")
    few = valued.count() <= BROADCAST_ROWS
    held = texts.join(F.broadcast(valued) if few else valued, texts.doc_id.eqNullSafe(valued.doc_id)).drop(valued.doc_id)
    held = held.withColumn("doc", tokens(F.col("text"))).drop("text").join(items, "item_id")
    said = lambda t: F.when(F.col("form") == 2, plain(t)).otherwise(t)
    pairs = F.transform("covered", lambda i: F.struct((F.substring(template(F.get("raw", i)), 1, 1) == SLOT).alias("slot"), said(F.get("raw", i)).alias("a"), said(F.get("doc", i + F.col("shift"))).alias("b")))
    held = held.select("doc_id", "item_id", "form", "covered", pairs.alias("all"))
    held = held.where((F.col("form") < 2) | F.forall("all", lambda p: p["slot"] | (p["a"] == p["b"])))
    pairs = F.array_distinct(F.transform(F.filter("all", lambda p: p["slot"]), lambda p: F.struct(p["a"].alias("a"), p["b"].alias("b"))))
    both = held.select("doc_id", "item_id", "covered", pairs.alias("p"))
    side = lambda k: F.size(F.array_distinct(F.transform("p", lambda p: p[k])))
    checked = both.where((side("a") == F.size("p")) & (side("b") == F.size("p"))).select("doc_id", "item_id", "covered", F.exists("p", lambda p: p["a"] != p["b"]).alias("changed"))
    kept = literal.unionByName(checked)
    length = items.select("item_id", F.size("raw").alias("n_tokens"))
    joined = kept.groupBy("doc_id", "item_id").agg(F.size(F.array_distinct(F.flatten(F.collect_set("covered")))).alias("matched"), F.max("changed").alias("reparameterised"))
    return joined.join(length, "item_id").where(F.col("matched") >= F.least(F.lit(MATCHED), "n_tokens")).select("doc_id", "item_id", F.col("matched").cast("long").alias("matched"), "n_tokens", "reparameterised")


def verdicts(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, contaminated, n_items, matched, item_id (the one matched most), reparameterised: one row per document."""
    found = materialise(contamination(docs, benchmark))
    per = found.groupBy(F.col("doc_id").alias("_d")).agg(F.count("*").alias("n_items"), F.max("matched").alias("matched"), F.max_by("item_id", F.struct("matched", -F.col("item_id"))).alias("item_id"), F.max("reparameterised").alias("reparameterised"))
    rows = docs.select("doc_id").join(per, F.col("doc_id").eqNullSafe(F.col("_d")), "left")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return rows.select("doc_id", F.col("n_items").isNotNull().alias("contaminated"), zero("n_items"), zero("matched"), "item_id", F.coalesce("reparameterised", F.lit(False)).alias("reparameterised"))


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents, all columns, without those that a benchmark item contaminates."""
    name = unused(docs, "_item")
    found = materialise(contamination(docs, benchmark).select(F.col("doc_id").alias(name)).distinct())
    return docs.join(found, docs["doc_id"].eqNullSafe(found[name]), "left_anti")


ship(__name__)
