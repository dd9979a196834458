"""Near-duplicate detection with SetSketch registers (operator 9).

A document is the set of its distinct five-word shingles (ASCII letters lower-cased,
words separated by ASCII white space).  Two documents are linked when
``100 * |A & B| >= 75 * |A | B|``; the operator returns the connected components.

How it runs
-----------
1. One pass over the texts (Arrow batches, numpy only) gives for every document the
   size of its set, a 128-bit digest of the set and ``BANDS * ROWS`` SetSketch
   registers.  A register holds the truncated, exponentially spaced minimum of
   exponential variates of the shingles: registers of a union are the maxima of the
   registers (mergeable), and equal registers are a locality-sensitive event of
   probability about J.
2. Rows with equal sets collapse onto one node (partial aggregation first, so a group of
   copies of any size is one row from here on).
3. Nodes meet in bands of four registers.  Each is first paired with one hub, the member
   of its buckets that has least of its own; pairs are screened by the joint
   maximum-likelihood estimate of J and confirmed on the whole sets.  A big group of near
   copies is one component after that.
4. What may still be linked across components is compared exactly, in one more step.
   Buckets of up to CROWD members give their pairs.  Members of larger buckets meet
   through their rarest shingles instead: with all sets ordered rarest shingle first, the
   first shingle that two linked sets have in common lies early in both, so a pair needs
   to be looked at only if it has a shingle at positions p and q with
   ``(100 + PERCENT) * min(n - p, m - q) >= PERCENT * (n + m)``.  Passages that thousands
   share come last in that order, and a set that has too much of its own never meets
   anyone.  The bound is exact: no candidate is dropped that it does not refute.

With 44 bands of 4 rows a link at J = 0.75 escapes all bands with probability
(1 - 0.75^4)^44 = 6e-8; links of higher similarity escape far less often.  The screen
is six standard deviations wide.

Defined results for odd rows: null, empty and white-space texts have an empty set
(n_shingles 0), are linked with nothing and are kept.  Rows that share a doc_id are one
document: equal texts count once, and sets of different texts of one doc_id lie in one
component.  A null doc_id keeps its row, with component_id null and kept true.  An empty
table gives an empty result.  Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialise, ship

WIDTH = 5
BANDS, ROWS = 44, 4
M = BANDS * ROWS
BASE = 1.001
RATE = 20.0
TOP = 65_535
PERCENT = 75
#: Members above which a bucket's pairs are found through rare shingles.
CROWD = 16
#: Bytes of text that one numpy pass holds.
CHUNK = 1 << 20

_rng = np.random.Generator(np.random.Philox(20_240_101))
BYTE = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
STEP = np.uint64(0x9E3779B97F4A7C15)
ORDER = _rng.integers(1, 1 << 63, WIDTH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
ODD = np.uint64(0xD1342543DE82EF95)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _word_hashes(raw: bytes) -> np.ndarray:
    """Hash of each word of a byte string, position by position within the word."""
    a = np.frombuffer(raw, np.uint8)
    space = (a == 32) | ((a >= 9) & (a <= 13))
    inside = ~space
    before = np.empty(len(a), bool)
    before[:1], before[1:] = False, inside[:-1]
    start = np.flatnonzero(inside & ~before)
    if not len(start):
        return np.empty(0, np.uint64)
    low = a + (((a >= 65) & (a <= 90)).view(np.uint8) << 5)
    first = np.repeat(start, np.diff(np.append(start, len(a))))
    at = np.arange(start[0], len(a)) - first
    power = np.multiply.accumulate(np.full(int(at.max()) + 1, ODD, np.uint64))
    value = BYTE[low[start[0] :]] * power[at]
    value[space[start[0] :]] = 0
    return mix(np.add.reduceat(value, start - start[0]))


def _pieces(raw: bytes) -> Iterator[bytes]:
    """Cut a long text at white space, so that no pass holds more than about CHUNK bytes."""
    at = 0
    while len(raw) - at > CHUNK:
        cut = max(raw.rfind(c, at, at + CHUNK) for c in (b" ", b"\n", b"\t", b"\r", b"\x0b", b"\x0c"))
        if cut <= at:  # one word longer than a chunk: extend to its end
            ends = [e for c in (b" ", b"\n", b"\t", b"\r", b"\x0b", b"\x0c") if (e := raw.find(c, at + CHUNK)) >= 0]
            cut = min(ends, default=len(raw))
        yield raw[at:cut]
        at = cut
    yield raw[at:]


def _sets_of(hashes: np.ndarray, n_words: np.ndarray) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of consecutive documents, given their word hashes."""
    n = len(hashes)
    wide = np.zeros(n, np.uint64)
    for k in range(min(WIDTH, n)):
        wide[: n - k] += hashes[k:] * ORDER[k]
    wide = mix(wide)
    out, at = [], 0
    for count in n_words.tolist():
        if count >= WIDTH:
            out.append(np.unique(wide[at : at + count - WIDTH + 1]))
        elif count:
            short = (hashes[at : at + count] * ORDER[:count]).sum(dtype=np.uint64)
            out.append(mix(np.array([short], np.uint64) + np.array([count], np.uint64) * STEP))
        else:
            out.append(np.empty(0, np.uint64))
        at += count
    return out


def shingle_sets(texts: list[bytes | None]) -> Iterator[tuple[int, list[np.ndarray]]]:
    """(index of the first document, sets) for runs of documents of about CHUNK bytes."""
    i = 0
    while i < len(texts):
        j, held = i, 0
        while j < len(texts) and (j == i or held + len(texts[j] or b"") <= CHUNK):
            held += len(texts[j] or b"") + 1
            j += 1
        run = [t or b"" for t in texts[i:j]]
        if j == i + 1 and len(run[0]) > CHUNK:
            words = [np.concatenate([_word_hashes(p) for p in _pieces(run[0])])]
        else:
            joined = b"\n".join(run) + b"\n"
            hashes = _word_hashes(joined)
            counts = np.array([len(t.split()) for t in run])
            words = np.split(hashes, np.cumsum(counts)[:-1])
        yield i, _sets_of(np.concatenate(words), np.array([len(w) for w in words]))
        i = j


def registers(sets: list[np.ndarray]) -> np.ndarray:
    """SetSketch registers, uint16 [documents, M]; all zero for an empty set.

    Every shingle owns a fixed Poisson process of rate M on the half line; each of its
    points belongs to one register.  That gives each register an independent unit
    exponential per shingle, and only the points below a bound that falls with the
    size of the set are ever generated.
    """
    size = np.array([len(s) for s in sets])
    reg = np.zeros((len(sets), M), np.uint16)
    todo = np.flatnonzero(size)
    bound = np.zeros(len(sets))
    bound[todo] = (np.log(M) + 3) / size[todo]
    flat = reg.reshape(-1)
    scale = 1 / np.log(BASE)
    while len(todo):
        for few in (True, False):
            docs = todo[(M * bound[todo] > 8) == few]
            if not len(docs):
                continue
            element = np.concatenate([sets[d] for d in docs])
            owner = np.repeat(docs, size[docs])
            x, j, block = np.zeros(len(element)), 0, 32 if few else 1
            while len(element):
                step = (np.arange(j + 1, j + block + 1, dtype=np.uint64) * STEP)[None, :]
                h = mix(element[:, None] + step)
                gap = np.log((h >> np.uint64(11)).astype(np.float64) + 1.0)
                gap = (53 * np.log(2.0) - gap) / M
                gap[:, 0] += x
                point = np.cumsum(gap, axis=1)
                below = point <= bound[owner][:, None]
                row, col = np.nonzero(below)
                where = mix(h[row, col] + ODD) % np.uint64(M)
                value = np.floor(1 - np.log(np.maximum(point[row, col], 1e-300) / RATE) * scale)
                np.maximum.at(flat, owner[row] * M + where.astype(np.int64), np.clip(value, 1, TOP).astype(np.uint16))
                go = below[:, -1]
                element, owner, x, j = element[go], owner[go], point[go, -1], j + block
        todo = todo[(reg[todo] == 0).any(axis=1)]
        bound[todo] *= 2
    return reg


def joint_estimate(a: np.ndarray, b: np.ndarray, na: np.ndarray, nb: np.ndarray) -> np.ndarray:
    """Maximum-likelihood J of pairs of sketches whose set sizes are known.

    Per register only "first larger", "second larger" or "equal" is informative; the
    likelihood of the three counts is concave in J, so a ternary search finds it.
    """
    up, down = (a > b).sum(axis=1), (a < b).sum(axis=1)
    same = a.shape[1] - up - down
    u, v = na / (na + nb), nb / (na + nb)
    prob = lambda x: np.clip(-np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / np.log(BASE), 1e-12, 1)

    def likelihood(j: np.ndarray) -> np.ndarray:
        p, q = prob(u - v * j), prob(v - u * j)
        return up * np.log(p) + down * np.log(q) + same * np.log(np.clip(1 - p - q, 1e-12, 1))

    lo, hi = np.zeros(len(u)), np.minimum(u / v, v / u)
    for _ in range(40):
        x, y = lo + (hi - lo) / 3, hi - (hi - lo) / 3
        left = likelihood(x) > likelihood(y)
        hi, lo = np.where(left, y, hi), np.where(left, lo, x)
    return (lo + hi) / 2


def _binary(batch: pa.RecordBatch, name: str) -> list[bytes | None]:
    column = batch.column(batch.schema.get_field_index(name))
    return column.cast(pa.large_binary()).to_pylist()


def _sketch_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, sets in shingle_sets(_binary(batch, "text")):
            n = np.array([len(s) for s in sets])
            every = np.concatenate(sets) if len(sets) else np.empty(0, np.uint64)
            at = np.concatenate([[0], np.cumsum(n)[:-1]]).astype(np.int64)
            one, two = np.zeros(len(n), np.uint64), np.zeros(len(n), np.uint64)
            has = n > 0
            if has.any():
                one[has] = np.add.reduceat(mix(every + STEP), at[has])
                two[has] = np.bitwise_xor.reduceat(mix(every ^ ODD), at[has])
            reg = registers(sets)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(i, len(sets)), batch.column(1).slice(i, len(sets)), pa.array(n, pa.int64()), pa.array(one.view(np.int64)), pa.array(two.view(np.int64)), pa.array([r.tobytes() for r in reg], pa.binary())],
                names=["doc_id", "mark", "n_shingles", "d1", "d2", "reg"],
            )


def sketch(docs: DataFrame) -> DataFrame:
    """(doc_id, mark, n_shingles, d1, d2, reg) of every row; ``mark`` tells texts of one doc_id apart."""
    return docs.select("doc_id", "mark", "text").mapInArrow(_sketch_batches, "doc_id long, mark long, n_shingles long, d1 long, d2 long, reg binary")


def _band_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    salt = mix(np.arange(1, BANDS + 1, dtype=np.uint64) * STEP)
    for batch in batches:
        if not batch.num_rows:
            continue
        reg = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint16).reshape(-1, BANDS, ROWS).astype(np.uint64)
        key = reg[:, :, 0] | (reg[:, :, 1] << np.uint64(16)) | (reg[:, :, 2] << np.uint64(32)) | (reg[:, :, 3] << np.uint64(48))
        key = mix(mix(key) + salt[None, :])
        node = np.repeat(batch.column(0).to_numpy(zero_copy_only=False), BANDS)
        yield pa.RecordBatch.from_arrays([pa.array(key.reshape(-1).view(np.int64)), pa.array(node)], names=["band", "node"])


def _likely_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    floor = PERCENT / 100 - 6 * (PERCENT / 100 * (1 - PERCENT / 100) / M) ** 0.5
    for batch in batches:
        if not batch.num_rows:
            continue
        x, y = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint16).reshape(-1, M) for k in (2, 3))
        na, nb = (batch.column(k).to_numpy(zero_copy_only=False).astype(float) for k in (4, 5))
        good = joint_estimate(x, y, na, nb) >= floor
        yield pa.RecordBatch.from_arrays([batch.column(k).filter(pa.array(good)) for k in (0, 1)], names=["a", "b"])


def _confirm_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (a, block, side): the hub's text, then the texts it is compared with."""
    hub, hub_set = None, np.empty(0, np.uint64)
    for batch in batches:
        key, node, side = (batch.column(k).to_pylist() for k in (0, 2, 3))
        a, b = [], []
        for i, sets in shingle_sets(_binary(batch, "text")):
            for k, own in enumerate(sets, i):
                if side[k] == 0:
                    hub, hub_set = key[k], own
                    continue
                assert hub == key[k]
                at = np.searchsorted(hub_set, own)
                at[at == len(hub_set)] = 0
                common = int((hub_set[at] == own).sum()) if len(hub_set) else 0
                if 100 * common >= PERCENT * (len(hub_set) + len(own) - common):
                    a.append(key[k])
                    b.append(node[k])
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def confirm(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (a, b) that are links, compared on their whole sets; ``texts`` is (node, text).

    A hub's partners are dealt into blocks of about 64, each with one copy of the hub's
    text, so a hub with a million partners is many small groups.
    """
    per = pairs.groupBy("a").agg(F.ceil(F.count("*") / 64).alias("blocks"))
    dealt = pairs.join(per, "a").select("a", F.pmod(F.xxhash64("b"), F.col("blocks")).alias("block"), "b")
    sides = dealt.select("a", "block", F.col("a").alias("node"), F.lit(0).alias("side")).distinct().unionByName(dealt.select("a", "block", F.col("b").alias("node"), F.lit(1).alias("side")))
    rows = sides.join(texts, "node").repartition("a", "block").sortWithinPartitions("a", "block", "side")
    return rows.select("a", "block", "node", "side", "text").mapInArrow(_confirm_batches, "a long, b long")


def _set_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, sets in shingle_sets(_binary(batch, "text")):
            ends = np.cumsum([0] + [len(s) for s in sets])
            for low in range(0, len(sets), 256):  # list offsets are 32 bits wide
                part = sets[low : low + 256]
                at = pa.array(ends[low : low + len(part) + 1] - ends[low], pa.int32())
                members = pa.ListArray.from_arrays(at, pa.array(np.concatenate(part).view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i + low, len(part)), members], names=["node", "members"])


def common_with_others(crowd: DataFrame, texts: DataFrame) -> DataFrame:
    """(node, shingle, held): the shingles of ``crowd``'s sets that ``held`` > 1 of them have."""
    sets = materialise(texts.join(crowd, "node", "left_semi").select("node", "text").mapInArrow(_set_batches, "node long, members array<long>"))
    each = sets.select("node", F.explode("members").alias("shingle"))
    held = each.groupBy("shingle").agg(F.count("*").alias("held")).where("held > 1")
    return materialise(each.join(held, "shingle").select("node", "shingle", "held"))


def prefixes(common: DataFrame, sizes: DataFrame) -> DataFrame:
    """(shingle, node, n, p): where a set's first shingle in common with a linked set may lie.

    Shingles that nobody else has take the first places, then come the others, rarest
    first.  A linked set has at least PERCENT per cent of the n members from there on.
    """
    known = common.join(common.groupBy("node").agg(F.count("*").alias("shared")).join(sizes, "node").where(f"100 * shared >= {PERCENT} * n"), "node")
    rank = F.row_number().over(Window.partitionBy("node").orderBy("held", "shingle"))
    return known.select("shingle", "node", "n", (F.col("n") - F.col("shared") + rank - 1).alias("p")).where(f"100 * p <= {100 - PERCENT} * n")


def early_pairs(early: DataFrame) -> DataFrame:
    """Pairs (a, b) of nodes of different components that have an early shingle in common.

    ``early`` is (shingle, node, n, p, comp).  A shingle's holders mostly belong to one
    component; only those outside it are met with the others, and only if the shortest
    holder is short enough for them.
    """
    per = early.groupBy("shingle", "comp").agg(F.count("*").alias("k"), F.min("n").alias("short"))
    mixed = per.groupBy("shingle").agg(F.max_by("comp", F.struct("k", "comp")).alias("main"), F.min("short").alias("short"), F.count("*").alias("kinds")).where("kinds > 1")
    fits = lambda n, p, m: f"{100 + PERCENT} * ({n} - {p}) >= {PERCENT} * ({n} + {m})"
    out = early.join(mixed, "shingle").where(F.expr("comp != main") & F.expr(fits("n", "p", "short")))
    out = out.select("shingle", F.col("node").alias("x"), F.col("n").alias("nx"), F.col("p").alias("px"), F.col("comp").alias("cx"))
    met = out.join(early, "shingle").where(F.expr("comp != cx") & F.expr(fits("nx", "px", "n")) & F.expr(fits("n", "p", "nx")))
    return met.select(F.least("x", "node").alias("a"), F.greatest("x", "node").alias("b"))


def bucket_pairs(met: DataFrame) -> DataFrame:
    """Pairs (a, b) of different components within the buckets of at most CROWD members."""
    few = met.where(f"m <= {CROWD}").select("band", "node", "n", "comp")
    mixed = few.groupBy("band").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low < high").select("band")
    few = few.join(mixed, "band", "left_semi")
    other = few.select("band", F.col("node").alias("b"), F.col("n").alias("nb"), F.col("comp").alias("cb"))
    close = F.expr(f"100 * least(n, nb) >= {PERCENT} * greatest(n, nb)")
    return few.join(other, "band").where(F.expr("node < b and comp != cb") & close).select(F.col("node").alias("a"), "b")


def components(edges: DataFrame) -> DataFrame:
    """(node, comp): the smallest node reachable, for every node of an edge.

    Min-label propagation with pointer jumping; each round is a partial aggregation
    and two joins, written to the shared folder.  Nothing is collected but a count.
    """
    both = materialise(edges.select("a", "b").union(edges.select("b", "a")).distinct())
    label = materialise(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("comp")))
    while True:
        near = both.join(label, both.b == label.node).groupBy("a").agg(F.min("comp").alias("seen"))
        step = label.join(near, label.node == near.a).select("node", "comp", F.least("comp", "seen").alias("next"))
        hop = label.select(F.col("node").alias("next"), F.col("comp").alias("jump"))
        after = materialise(step.join(hop, "next", "left").select("node", F.least("next", F.coalesce("jump", "next")).alias("comp"), (F.least("next", F.coalesce("jump", "next")) != F.col("comp")).alias("moved")))
        moved = after.where("moved").limit(1).count()
        label = after.select("node", "comp")
        if not moved:
            return label


def _same_document(rows: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges (a, b) between the sets of a doc_id that occurs with several."""
    key = ["n_shingles", "d1", "d2"]
    several = rows.groupBy("doc_id").agg(F.min(F.struct(*key)).alias("low"), F.max(F.struct(*key)).alias("high")).where("low < high").select("doc_id")
    held = materialise(rows.join(several, "doc_id", "left_semi").select("doc_id", *key).distinct().join(nodes.select("node", *key), key))
    first = held.groupBy("doc_id").agg(F.min("node").alias("a"))
    return held.join(first, "doc_id").where("a < node").select("a", F.col("node").alias("b"))


def linked(pairs: DataFrame, company: DataFrame, texts: DataFrame) -> DataFrame:
    """Those of the pairs (a, b) that are links: screened by their sketches, confirmed on their sets."""
    side = lambda n: company.select(F.col("node").alias(n), F.col("reg").alias(f"r{n}"), F.col("n").alias(f"n{n}"))
    sized = pairs.join(side("a"), "a").join(side("b"), "b").where(f"100 * least(na, nb) >= {PERCENT} * greatest(na, nb)")
    likely = materialise(sized.select("a", "b", "ra", "rb", "na", "nb").mapInArrow(_likely_batches, "a long, b long"))
    return materialise(confirm(likely, texts))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of ``docs``."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("mark", F.xxhash64("text"))
    rows = materialise(sketch(docs))
    some = rows.where("n_shingles > 0 and doc_id is not null")
    groups = some.groupBy("n_shingles", "d1", "d2").agg(F.min(F.struct("doc_id", "mark")).alias("rep"), F.count("*").alias("copies"), F.first("reg").alias("reg"))
    nodes = materialise(groups.select(F.monotonically_increasing_id().alias("node"), "n_shingles", "d1", "d2", "rep.doc_id", "rep.mark", "copies", "reg"))
    bands = materialise(nodes.select("node", "reg").mapInArrow(_band_batches, "band long, node long"))
    met = materialise(bands.join(bands.groupBy("band").agg(F.count("*").alias("m")).where("m > 1"), "band"))
    company = materialise(nodes.join(met.select("node").distinct(), "node", "left_semi").select("node", F.col("n_shingles").alias("n"), "reg", "doc_id", "mark"))
    # the one shuffle of whole texts before comparison: one text of each set that meets others
    texts = materialise(docs.join(company.select("doc_id", "mark", "node"), ["doc_id", "mark"]).select("node", "text").dropDuplicates(["node"]))
    common = common_with_others(met.where(f"m > {CROWD}").select("node").distinct(), texts)
    sizes = company.select("node", "n")
    shared = common.groupBy("node").agg(F.count("*").alias("shared"))
    met = met.join(sizes, "node").join(shared, "node", "left")
    met = materialise(met.select("band", "m", "node", "n", F.coalesce(1 - F.col("shared") / F.col("n"), F.lit(0.0)).alias("own")))
    # every node tries one hub: of the members it meets, the one with least of its own
    hub = met.groupBy("band").agg(F.min(F.struct("own", "node")).alias("hub"))
    star = met.join(hub, "band").where(F.col("node") != F.col("hub.node")).groupBy("node").agg(F.min("hub").alias("hub"))
    star = materialise(star.select(F.col("hub.node").alias("a"), F.col("node").alias("b")))
    links = linked(star, company, texts).unionByName(_same_document(some, nodes))
    label = components(links)
    placed = lambda df: df.join(label, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    rest = bucket_pairs(placed(met)).unionByName(early_pairs(materialise(placed(prefixes(common, sizes))))).distinct()
    more = linked(materialise(rest), company, texts)
    label = components(links.unionByName(more))
    first = nodes.join(label, "node").groupBy("comp").agg(F.min("doc_id").alias("component_id"))
    one = label.join(first, "comp").select("node", "component_id")
    known = nodes.join(one, "node", "left").where("copies > 1 or component_id is not null").select("d1", "d2", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
    out = rows.select("doc_id", "n_shingles", "d1", "d2").join(known, ["d1", "d2", "n_shingles"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


ship(__name__)
