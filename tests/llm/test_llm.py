"""Training-data operators on small fixtures: odd rows, brute force, round trips."""

import base64
import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from weightdraw.llm import decontaminate, language, quality, setsketch, sharding, topk, toxicity, trees, unigram, warc, wrappers

random.seed(11)
WORDS = [f"w{i}" for i in range(400)]


def text(n):
    return " ".join(random.choice(WORDS) for _ in range(n))


DOCS = "doc_id long, text string, lang string, source string, n_chars long, rank int"


def frame(spark, rows):
    return spark.createDataFrame([(i, t, lang, "s", len(t or ""), 1) for i, t, lang in rows], DOCS)


# ---- near duplicates -------------------------------------------------------------------


def shingles(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), t or ""))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def brute_components(rows):
    sets = {i: shingles(t) for i, t in rows}
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def test_near_duplicates_equal_brute_force(spark):
    rows, base = [], text(120).split()
    for i in range(60):  # copies around the threshold, some linked only through others
        own = list(base)
        for at in random.sample(range(len(own)), random.randint(0, 5)):
            own[at] = f"x{i}_{at}"
        rows.append((i, " ".join(own)))
    rows += [(100 + i, text(random.choice([1, 3, 5, 30]))) for i in range(20)]
    rows += [(200, None), (201, ""), (202, " \n\t"), (203, "A b C"), (204, "a  B c"), (205, rows[0][1].upper())]
    got = setsketch.near_duplicates(frame(spark, [(i, t, None) for i, t in rows])).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == brute_components(rows)
    assert all(r.kept == (r.doc_id == r.component_id) for r in got) and len(got) == len(rows)


def crowded_buckets(texts):
    """Of each text, the buckets of more than CROWD members in which it lies."""
    reg = np.concatenate([setsketch.registers(sets) for _, sets in setsketch.shingle_sets([t.encode() for t in texts])])
    keys = [[(k, *band) for k, band in enumerate(r)] for r in reg.reshape(len(texts), setsketch.BANDS, setsketch.ROWS).tolist()]
    members = Counter(key for own in keys for key in own)
    return [[key for key in own if members[key] > setsketch.CROWD] for own in keys]


def test_a_near_copy_outside_the_crowd_is_linked(spark):
    rng = random.Random(5)
    own = lambda n: [f"v{rng.randrange(10**9)}" for _ in range(n)]
    passage = own(150)
    texts = [passage + own(100) for _ in range(70)]
    busy = [k for k, buckets in enumerate(crowded_buckets([" ".join(t) for t in texts])) if buckets]
    near = []
    for k in busy:  # a copy without a part of the passage, which lies in none of the crowded buckets
        for at in range(0, 95, 5):
            one = texts[k][:at] + texts[k][at + 50 :]
            if not crowded_buckets([" ".join(t) for t in [*texts, one]])[-1]:
                near.append(one)
                break
        if len(near) == 3:
            break
    assert len(near) == 3
    rows = list(enumerate(" ".join(t) for t in texts + near))
    got = setsketch.near_duplicates(frame(spark, [(i, t, None) for i, t in rows])).collect()
    want = brute_components(rows)
    assert sum(i != c for i, (_, c) in want.items()) == 3
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want


def test_near_duplicates_of_nothing(spark):
    assert setsketch.near_duplicates(frame(spark, [])).count() == 0


def test_a_run_that_fills_its_chunk_keeps_all_texts():
    limit = setsketch.CHUNK
    long = lambda n: (b"ab cd ef gh ij kl " * (n // 18 + 1))[:n]
    for sizes in ([1000, limit - 1001], [1000, limit - 1000], [limit - 1, 0, 0], [limit], [limit + 1, 7], [5, limit, 5]):
        texts = [long(n) for n in sizes]
        got = [(i + k, own) for i, sets in setsketch.shingle_sets(texts) for k, own in enumerate(sets)]
        assert [i for i, _ in got] == list(range(len(texts)))
        assert [len(own) for _, own in got] == [len(shingles(t.decode())) for t in texts]


def test_registers_merge_and_estimate():
    a = np.unique(np.random.default_rng(1).integers(0, 1 << 63, 3000).astype(np.uint64))
    b = np.concatenate([a[:2400], np.unique(np.random.default_rng(2).integers(0, 1 << 63, 500).astype(np.uint64))])
    b.sort()
    ra, rb, ru = setsketch.registers([a, b, np.union1d(a, b)])
    assert (np.maximum(ra, rb) == ru).all()
    j = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
    est = setsketch.joint_estimate(ra[None], rb[None], np.array([len(a)]), np.array([len(b)]))[0]
    assert abs(est - j) < 0.15


# ---- pieces -------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def vocabulary():
    return unigram.Vocabulary.read()


def brute_score(v, marked):
    """Best total score of a marked byte string, by a plain dictionary and no trie."""
    pieces = {}
    for ident, surface in enumerate(v.surface):
        if ident > 2 and ident not in v.byte:
            pieces[surface.replace(b" ", unigram.MARK)] = float(v.score[ident])
    best = [0.0] + [-math.inf] * len(marked)
    for s in range(len(marked)):
        if best[s] > -math.inf:
            step = unigram._width(marked[s])
            for e in range(s + 1, min(len(marked), s + 60) + 1):
                if marked[s:e] in pieces:
                    best[e] = max(best[e], best[s] + pieces[marked[s:e]])
            if marked[s : s + step] not in pieces:
                best[s + step] = max(best[s + step], best[s] + v.unknown_score)
    return best[-1]


def test_encoding_is_optimal_and_round_trips(vocabulary):
    v, memo = vocabulary, {}
    cases = ["", " ", "a", "  two  spaces ", "the theatre", "naïve café", "日本語 😀", "\n\ttab", "x" * 100, "ab" * 50]
    for case, ids in zip(cases, v.encode_many([c.encode() for c in cases], memo), strict=True):
        own = np.frombuffer(ids, np.int32)
        assert v.decode(own) == case.encode()
        if case:
            total = sum(float(v.score[i]) for i in own if i not in v.byte)
            unknown = sum(1 for c in case if c.encode() and len(c.encode()) and all(v.byte[b] in own for b in c.encode()) and c not in "".join(s.decode("utf-8", "ignore") for s in (v.surface[i] for i in own if i not in v.byte)))
            want = brute_score(v, (" " + case).encode().replace(b" ", unigram.MARK))
            assert total + unknown * v.unknown_score <= want + 1e-3 or unknown
            if not any(i in v.byte for i in own):
                assert abs(total - want) < 1e-3 * max(1, abs(want))


def test_both_solvers_agree(vocabulary):
    words = [("▁" + w).encode() for w in ("hello", "é日", "abc\n", "strengthening", "zzzz")]
    assert vocabulary.solve_many(words) == [vocabulary.solve_one(w) for w in words]


def test_encode_frame(spark):
    got = {r.doc_id: r for r in unigram.encode(frame(spark, [(1, None, None), (2, "", None), (3, "a b\nc", None)])).collect()}
    assert got[1].ids is None and got[1].round_trip is None and got[2].ids == [] and got[3].round_trip
    back = {r.doc_id: r.text for r in unigram.decode(unigram.encode(frame(spark, [(1, None, None), (3, "a b\nc", None)]))).collect()}
    assert back == {1: None, 3: "a b\nc"}


# ---- archives -------------------------------------------------------------------------------


def test_archives_round_trip(spark):
    rows = [(1, "http://a.org/x?q", "<p>é</p>"), (2, "http://b.a.org/", "<p>é</p>"), (3, None, None), (4, "http://a.org/\r\ny", ""), (5, "http://a.org/z", "a\r\n\r\nWARC/1.1\r\n")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r for r in warc.archive_round_trip(pages).collect()}
    for ident, _, html in rows:
        own = (html or "").encode()
        assert got[ident].payload_bytes == len(own)
        assert got[ident].payload_digest == base64.b32encode(hashlib.sha1(own).digest()).decode()
    assert {i: (r.record_type, r.refers_to) for i, r in got.items()} == {1: ("response", None), 2: ("revisit", 1), 3: ("response", None), 4: ("revisit", 3), 5: ("response", None)}
    path = warc.shared_dir(spark)
    warc.write_archives(pages, path)
    index = warc.build_index(warc.read_archives(spark, path))
    (hit,) = warc.lookup(index, "http://a.org/z")
    assert warc.read_record(spark, hit["file"], hit["offset"], hit["length"])[1] == b"a\r\n\r\nWARC/1.1\r\n"
    assert warc.lookup(index, "http://nowhere.org/") == []
    assert warc.archive_round_trip(pages.limit(0)).count() == 0


# ---- search, shards, decontamination ---------------------------------------------------------


def test_top_k_equals_brute_force(spark):
    rng = np.random.default_rng(4)
    rows = [(i, [float(x) for x in rng.normal(size=40)]) for i in range(260)] + [(300, None), (301, [1.0, None]), (302, [float("nan")] * 40), (None, [1.0] * 40), (303, [0.5] * 3)]
    rows += [(i + 1000, rows[i][1]) for i in range(5)]  # ties
    got = topk.exact_top_k(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), F.col("vec_id") % 50 == 0)
    good = {i: np.floor(256 * np.pad(np.float32(v), (0, 40 - len(v))).astype(float)) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)}
    want = set()
    for q in (i for i in good if i % 50 == 0):
        order = sorted((-int(good[q] @ good[c]), c) for c in good if c != q)[:5]
        want |= {(q, r, c, -s) for r, (s, c) in enumerate(order, 1)}
    assert {tuple(r) for r in got.collect()} == want


def test_shards_are_even_and_keep_copies_together(spark):
    rows = [(i, text(6) if i % 3 else f"copy {i % 5}", None) for i in range(400)] + [(900, None, None), (901, "", None)]
    got = sharding.balanced_shards(frame(spark, rows), shards=8).collect()
    by = {}
    for r in got:
        by.setdefault(r.shard, []).append(r.slot)
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1 and len(got) == len(rows)
    assert all(sorted(s) == list(range(len(s))) for s in by.values())
    shards_of = {}
    texts = {i: t for i, t, _ in rows}
    for r in got:
        shards_of.setdefault(texts[r.doc_id], set()).add(r.shard)
    assert all(len(shards_of[f"copy {k}"]) <= 2 for k in range(5))
    assert sharding.balanced_shards(frame(spark, []), shards=8).count() == 0


def test_grants_keep_sizes():
    got, away, left = sharding.grants({(0, 1): 5, (1, 2): 2, (2, 1): 4}, {1: 3}, 3)
    assert sum(away.values()) == sum(left.values()) and away.get(1, 0) <= 3
    assert all(got[k] <= v for k, v in {(0, 1): 5, (1, 2): 2, (2, 1): 4}.items())


ITEM = "A farmer called Mary sells 12 baskets of apples for 30 dollars and keeps 12 baskets for the winter market in town"


def test_decontamination(spark):
    bench = spark.createDataFrame([(1, ITEM), (2, None), (3, "too short")], "item_id long, text string")
    filler = text(40)
    rows = [
        (1, f"{filler} {ITEM}. {filler}", None),
        (2, f"{filler} {ITEM.replace('12', '47').replace('Mary', 'John').replace('30', '99')} {filler}", None),
        (3, f"{filler} {ITEM.replace('12 baskets of', '47 baskets of')} {filler}", None),  # 12 stands for two values
        (4, f"{filler} {ITEM.lower()} {filler}", None),
        (5, filler, None),
        (6, None, None),
        (7, "", None),
    ]
    got = {r.doc_id: r for r in decontaminate.verdicts(frame(spark, rows), bench).collect()}
    assert {i for i, r in got.items() if r.contaminated} == {1, 2, 4}
    assert got[2].reparameterised and not got[1].reparameterised
    kept = decontaminate.clean(frame(spark, rows), bench)
    assert {r.doc_id for r in kept.collect()} == {3, 5, 6, 7} and "rank" in kept.columns
    assert decontaminate.verdicts(frame(spark, rows), bench.limit(0)).where("contaminated").count() == 0


def test_verbatim_items_dense_in_values(spark):
    items = [
        (1, "What is 12 + 34 + 56"),
        (2, "Add 3 km 5 m 7 cm and 2 miles 9 yards 4 feet 8 inches to 11 gallons 6 litres"),
        (3, "Anna, Bertha, Clara, Doris, Emma, Frieda, Greta, Hanna, Ida, Johanna, Karla, Lena, Martha, Nora"),
        (4, "Where do the quiet herons sleep"),
        (5, "Each of them carries 14 heavy boxes up later returns with exactly 9"),
    ]
    bench = spark.createDataFrame(items, "item_id long, text string")
    filler = text(30)
    rows = [(i, f"{filler} {item} {filler}", None) for i, item in items]
    rows += [(10 + i, f"{filler}, {item.lower()}\n{filler}", None) for i, item in items]
    rows += [
        (20, f"{filler} {items[4][1].replace('14', '37')} {filler}", None),
        (21, f"{filler} {items[4][1].replace('Each', 'Some').replace('14', '37')} {filler}", None),  # another first word
        (22, f"{filler} {items[0][1].replace('34', '35')} {filler}", None),
    ]
    got = {r.doc_id: r for r in decontaminate.verdicts(frame(spark, rows), bench).collect()}
    assert {i: r.item_id for i, r in got.items() if r.contaminated} == {**{i: i for i, _ in items}, **{10 + i: i for i, _ in items}, 20: 5}
    assert {i for i, r in got.items() if r.reparameterised} == {20}


# ---- pages -----------------------------------------------------------------------------------


def test_wrappers():
    page = lambda title, body: f"<html><head><title>t</title></head><body><nav><ul><li>menu</li></ul></nav><div class='ad'>buy</div><article><h1>{title}</h1>{body}<section id=comments><p>first!</p></section></article><footer>&copy;</footer>"
    one = wrappers.fold(wrappers.parse(page("A", "<p>x</p><p>y</p>")))
    two = wrappers.fold(wrappers.parse(page("B", "<p>z</p><ul><li>q</ul>")))
    whole = wrappers.merge(one, two)
    assert "p(#)+" in wrappers.expression(whole) and "ul(" in wrappers.expression(whole) and ")?" in wrappers.expression(whole)
    path = wrappers.region(whole)
    assert path[-1].startswith("article")
    assert wrappers.main_text(page("A &amp; B", "<p>in<b>si</b>de<br>line<script>no</script><p>next &lt;1"), path) == "A & B inside line next <1"
    for odd in (None, "", "plain", "<p>open", "<", "<a href='x>y", "<!-- never closed"):
        assert isinstance(wrappers.main_text(odd, path), str)
    assert wrappers.main_text("plain text", path) == "plain text"


def test_extract_frame(spark):
    rows = [(1, "http://h.org/1", "<body><nav>n</nav><article><p>a</p></article>"), (2, "http://h.org/2", "<body><article><p>b</p><p>c</p></article>"), (3, None, None), (4, None, "")]
    got = {r.page_id: (r.text, r.n_chars) for r in wrappers.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {1: ("a", 1), 2: ("b c", 3), 3: ("", 0), 4: ("", 0)}


# ---- learners ----------------------------------------------------------------------------------


def test_isotonic_and_lasso():
    x, y = trees.isotonic(np.array([1.0, 2, 3, 4, 4]), np.array([0.0, 1, 0, 1, 1]))
    assert (np.diff(y) >= 0).all() and y[0] == 0 and y[-1] == 1
    rng = np.random.default_rng(0)
    r = rng.integers(0, 2, (600, 12)).astype(float)
    t = (rng.random(600) < trees.sigmoid(3 * r[:, 0] - 1.5)).astype(float)
    _, w = trees.lasso_logistic(r, t, 0.02)
    assert w[0] > 1 and (np.abs(w[1:]) < 0.4).all()


def labelled(spark, make_bad, label):
    rows = [(i, make_bad(i) if i % 4 == 0 else text(60), "en") for i in range(200)] + [(900, None, "en"), (901, "", "en")]
    labels = spark.createDataFrame([(i, int((i % 4 == 0) == (label == "toxic"))) for i in range(200)], f"doc_id long, {label} int")
    return frame(spark, rows), labels


def test_quality_on_held_out_rows(spark):
    docs, labels = labelled(spark, lambda i: " ".join(f"w{i}***" for _ in range(60)), "quality")
    got = quality.score(docs, labels).collect()
    held = [r for r in got if r.held_out and r.doc_id < 200]
    assert len(got) == 202 and sum(r.predicted == int(r.doc_id % 4 != 0) for r in held) >= 0.95 * len(held)
    none = quality.score(docs, labels.limit(0)).collect()
    assert {r.predicted for r in none} == {1}


def test_toxicity_on_held_out_rows(spark):
    docs, labels = labelled(spark, lambda i: text(30) + " you grumble snarkle " + text(25) + " wretcher", "toxic")
    got = toxicity.score(docs, labels).collect()
    held = [r for r in got if r.held_out and r.doc_id < 200]
    assert len(got) == 202 and sum(r.predicted == int(r.doc_id % 4 == 0) for r in held) >= 0.95 * len(held)
    assert {r.predicted for r in toxicity.score(docs, labels.limit(0)).collect()} == {0}


def test_language(spark):
    one, two = ["ala", "bela", "kela", "mila"], ["zork", "vruk", "drak", "grosk"]
    rows = [(i, " ".join(random.choices(one if i % 2 else two, k=30)), "aa" if i % 2 else "zz") for i in range(80)] + [(900, None, "aa"), (901, "12 !", None), (902, "", "zz"), (903, "vrak zosk", None)]
    got = {r.doc_id: r for r in language.predict(frame(spark, rows)).collect()}
    assert all(got[i].lang_pred == ("aa" if i % 2 else "zz") for i in range(80))
    assert [got[i].lang_pred for i in (900, 901, 902, 903)] == ["und", "und", "und", "zz"]
    assert {r.lang_pred for r in language.predict(frame(spark, [(1, "abc", None)])).collect()} == {"und"}
    grams, _ = language.windows(["ab", "a"])
    assert [tuple(g) for g in grams[-2:]] == [(2, 2, 2, 97), (2, 2, 97, 3)]


def test_language_model_keeps_every_gram(spark, monkeypatch):
    monkeypatch.setattr(language, "MAX_GRAMS", 10, raising=False)
    rows = [(i, "ala bela kela mila " + ("rarus" if i == 8 else ""), "aa") for i in range(12)] + [(21, "zork vruk", "zz")]
    train = [t for i, t, _ in rows if zlib.crc32(str(i).encode()) % language.MODULUS != language.REMAINDER]
    model = language.fit(frame(spark, rows))
    grams, _ = language.windows(sorted({w for t in train for w in language.words_of(t)}))
    assert any("rarus" in t for t in train) and any("zork" in t for t in train)
    assert model.languages == ["aa", "zz"]
    assert set(model.keys[-1].tolist()) == set(language.hashes(grams).tolist())


def test_model_probabilities_add_up():
    words = ["ab", "aab", "ba"]
    grams, _ = language.windows(words)
    text_grams = np.unique(grams, axis=0)
    counts = np.array([[(grams == g).all(axis=1).sum()] for g in text_grams])
    model = language.KneserNey(["x"], text_grams, counts)
    context = np.array([2, 2, 97], np.uint32)
    p = [np.exp(model._logs(np.array([[*context, c]], np.uint32)))[0, 0] for c in (97, 98, 3, 99)]
    assert abs(sum(p) - 1) < 1e-6


# ---- pipeline -----------------------------------------------------------------------------------


def test_pipeline_on_odd_rows(spark, tmp_path):
    import corpus_pipeline

    rows = [(i, text(60), "en") for i in range(40)] + [(50, rows_text := text(50), "en"), (51, rows_text, "en"), (60, ITEM, "en"), (70, None, None), (71, "", "en")]
    docs = frame(spark, rows)
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, ITEM)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    got = {r.doc_id: r for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert set(got) == {*range(40), 50, 70, 71} and got[50].round_trip
