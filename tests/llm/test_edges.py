"""Odd rows of every operator: empty tables, repeated rows, null ids, clashing columns, long and broken texts."""

import random
import re
import time
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_llm import DOCS, brute_components, frame, text

from weightdraw.llm import decontaminate, language, quality, setsketch, sharding, topk, toxicity, unigram, warc, wrappers

CLASHES = ("_w _hits _t_lexicon _t_words _quality _q_n_words _toxicity _gone _score _d n_words y entry node band comp mark shingle rep shard slot g h1 "
           "size law part item_id matched ids hash at score held_out predicted url path file").split()


def with_clashes(df):
    return df.withColumns({c: F.lit("kept") for c in CLASHES})


def labels_of(spark, ids, bad):
    return spark.createDataFrame([(i, int(i not in bad), int(i in bad)) for i in ids], "doc_id long, quality int, toxic int")


ODD = [(None, "a null id", None), (None, None, None), (1, None, "en"), (2, "", "en"), (3, "word " * 20_000, "en"), (4, "same text here", "en"), (4, "same text here", "en"), (5, "x" * 40_000, None)]


@pytest.fixture(scope="module")
def odd(spark):
    random.seed(3)
    rows = ODD + [(10 + i, text(40) + (" you wretched snarkle ***" if i % 4 == 0 else ""), "en" if i % 2 else "xx") for i in range(60)]
    docs = with_clashes(frame(spark, rows))
    labels = labels_of(spark, [r[0] for r in rows if r[0] is not None], {10 + i for i in range(0, 60, 4)})
    bench = spark.createDataFrame([(1, "What is 12 plus 35 minus 7 times 4 over 9 in all")], "item_id long, text string")
    return docs, labels, bench, rows


def ids(df):
    return Counter(r.doc_id for r in df.select("doc_id").collect())


def test_every_row_has_one_result(odd):
    docs, labels, bench, rows = odd
    want = Counter(r[0] for r in rows)
    assert ids(setsketch.near_duplicates(docs)) == want
    assert ids(quality.score(docs, labels)) == want
    assert ids(toxicity.score(docs, labels)) == want
    assert ids(language.predict(docs)) == want
    assert ids(decontaminate.verdicts(docs, bench)) == want
    assert ids(sharding.balanced_shards(docs, shards=7)) == want
    assert ids(unigram.encode(docs)) == want


def test_filters_keep_all_columns(odd):
    docs, labels, bench, _ = odd
    for kept in (quality.keep(docs, quality.fit(docs, labels)), toxicity.keep(docs, toxicity.fit(docs, labels)), decontaminate.clean(docs, bench)):
        assert kept.columns == docs.columns
        assert all(r[c] == "kept" for r in kept.limit(3).collect() for c in CLASHES)


def test_the_scores_do_not_depend_on_where_they_are_used(odd):
    docs, labels, _, _ = odd
    model = quality.fit(docs, labels)
    by_score = [r.doc_id for r in quality.score(docs, labels).where("predicted = 1").collect()]
    assert Counter(by_score) == ids(quality.keep(docs, model))
    plan = quality.keep(docs, model)._jdf.queryExecution().optimizedPlan().toString()
    assert len(re.findall("regexp_count", plan)) <= 10  # each statistic is in the plan once


def test_stages_one_by_one(spark, odd, tmp_path):
    import corpus_pipeline

    docs, labels, bench, rows = odd
    labels.write.parquet(str(tmp_path / "labels.parquet"))
    bench.write.parquet(str(tmp_path / "benchmark.parquet"))
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, str(tmp_path))
        assert name == "pieces" or out.columns == docs.columns, name
        if name == "near_duplicates":
            assert set(ids(out)) == {r[0] for r in rows}
        assert stage(spark, docs.limit(0), str(tmp_path)).count() == 0, name


def test_empty_tables(spark):
    none = frame(spark, [])
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    bench = spark.createDataFrame([], "item_id long, text string")
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    for df in (setsketch.near_duplicates(none), quality.score(none, labels), toxicity.score(none, labels), language.predict(none), decontaminate.verdicts(none, bench),
               sharding.balanced_shards(none), unigram.encode(none), wrappers.extract(pages), warc.archive_round_trip(pages),
               topk.exact_top_k(spark.createDataFrame([], "vec_id long, embedding array<float>"), F.col("vec_id") % 50 == 0)):
        assert df.count() == 0


# ---- near duplicates ------------------------------------------------------------------------


def test_boilerplate_with_planted_pairs(spark):
    rng = random.Random(9)
    own = lambda n: [f"v{rng.randrange(10**9)}" for _ in range(n)]
    passage, texts = own(90), []
    for i in range(700):
        body = passage + own(rng.choice([20, 60, 110, 200]))
        texts.append(body)
        if i % 10 == 0:  # a near copy: some words changed in its own part
            other = list(body)
            for at in rng.sample(range(90, len(body)), max(1, len(body) // 100)):
                other[at] = "changed"
            texts.append(other)
    rows = [(i, " ".join(t), None) for i, t in enumerate(texts)]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in setsketch.near_duplicates(frame(spark, rows)).collect()}
    want = brute_components([r[:2] for r in rows])
    assert sum(c != i for i, (_, c) in want.items()) >= 60
    assert got == want


def test_a_cluster_of_edited_copies(spark):
    """Copies with 0 to 30 per cent of edits: links, and pairs just below the threshold, across a crowd."""
    rng = random.Random(2)
    base, rows = [f"b{i}" for i in range(150)], []
    for i in range(300):
        own = list(base[: rng.randint(110, 150)])
        for at in rng.sample(range(len(own)), rng.randint(0, 8)):
            own[at] = f"e{rng.randrange(40)}"
        rows.append((i, " ".join(own), None))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in setsketch.near_duplicates(frame(spark, rows)).collect()}
    assert got == brute_components([r[:2] for r in rows])


def test_rows_of_one_document(spark):
    one, two, three = text(50), text(50), text(50)
    rows = [(5, one, None), (5, two, None), (2, two, None), (9, one, None), (7, three, None), (7, three, None), (None, one, None), (8, " ", None), (8, three, None)]
    got = sorted((r.doc_id or 0, r.n_shingles > 0, r.component_id, r.kept) for r in setsketch.near_duplicates(frame(spark, rows)).collect())
    assert got == sorted([(5, True, 2, False), (5, True, 2, False), (2, True, 2, True), (9, True, 2, False), (7, True, 7, True), (7, True, 7, True), (0, True, None, True), (8, False, 8, True), (8, True, 7, False)])


# ---- pages ------------------------------------------------------------------------------------


@pytest.mark.parametrize(
    ("page", "want"),
    [
        ("<div>" * 30_000 + "deep text" + "</div>" * 30_000 + "<p>after", "deep text after"),
        ("ahead " + "<a " * 200_000, "ahead"),
        ("<p>one" + '<a href="x' * 50_000, "one"),
        ("<p>one" + "<!" * 100_000, "one"),
        ("<p>x</p><a =" + '="a" ' * 100_000, "x"),
        ("<b><table>" + "<i>" * 20_000 + "</b>" * 20_000 + "x", "x"),
        ("<div>" * 300 + "<nav>menu<b>x</b></nav>main" + "</div>" * 300, "main"),
        ("<p title='a>b'>kept</p><p title = \"c>d\">too</p>", "kept too"),
        ("a < b and <3 c", "a < b and <3 c"),
        ("<ul>" + "<li>item <b>x</b>" * 20_000, " ".join(["item x"] * 20_000)),
    ],
)
def test_deep_long_and_broken_pages(page, want):
    start = time.time()
    assert wrappers.main_text(page, []) == want
    own = wrappers.fold(wrappers.parse(page))
    wrappers.expression(wrappers.json.loads(wrappers.json.dumps(wrappers.merge(own, wrappers.fold(wrappers.parse(page + "<p>y</p>"))))))
    assert time.time() - start < 60


def test_wide_levels_align_like_narrow_ones():
    for n in (5, 70, 400):
        a = wrappers.parse("".join(f"<h{i % 6 + 1} class='c{i}'>t</h{i % 6 + 1}>" for i in range(n) for i in [chr(97 + i % 26) and i]))
        names = [c.label for c in a.children]
        one = wrappers.fold(a)
        two = wrappers.fold(wrappers.parse("".join(f"<h{i % 6 + 1} class='c{i}'>t</h{i % 6 + 1}>" for i in range(n) if i != n // 2)))
        assert len(one[2]) == len(wrappers.repeated([[x, "", [], None, 0] for x in names]))
        whole = wrappers.merge(one, two)
        assert {k[1] for k in whole[2]} <= {"", "?", "+", "*"} and len(whole[2]) <= len(one[2])


def test_the_order_of_wrappers_does_not_matter():
    import pyarrow as pa

    pages = ["<div><p>a</p></div>", "<div><h2>t</h2><p>b</p><p>c</p></div>", "<div><ul><li>q</ul></div>", "<section>z</section>"]
    own = [wrappers.json.dumps(wrappers.fold(wrappers.parse(p))) for p in pages]
    group = lambda rows: wrappers._merge_group((pa.scalar("h"),), pa.table({"host": ["h"] * len(rows), "wrapper": rows})).column("wrapper")[0].as_py()
    assert len({group(random.sample(own, 4)) for _ in range(10)}) == 1


def test_unmarked_pages_take_the_varying_group():
    page = lambda t: f"<body><div class=x><p>{'furniture of the site ' * 30}</p></div><div class=y><p>{t}</p></div></body>"
    whole = wrappers.fold(wrappers.parse(page("first story of today, quite short")))
    for t in ("second story, about something else", "third"):
        whole = wrappers.merge(whole, wrappers.fold(wrappers.parse(page(t))))
    assert wrappers.main_text(page("fourth story"), wrappers.region(whole)) == "fourth story"


def test_pages_with_repeats_and_extra_columns(spark):
    rows = [(1, "http://h.org/1", "<article><p>a</article>", "k"), (1, "http://h.org/1", "<article><p>a</article>", "k"), (None, "::bad", "<p>b", "k"), (2, "", None, "k")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, path string").withColumn("_host", F.lit("x")).withColumn("text", F.lit("t"))
    got = sorted((r.page_id or 0, r.text, r.n_chars) for r in wrappers.extract(pages).collect())
    assert got == [(0, "b", 1), (1, "a", 1), (1, "a", 1), (2, "", 0)]


# ---- archives ----------------------------------------------------------------------------------


def test_archives_of_any_size(spark):
    rows = [(i, f"http://a.org/{i}", "x" * n) for i, n in enumerate([0, 10, 40_000, 40_000, 700_000, 9_000_000])] + [(None, "http://a.org/n", "y"), (50, "http://a.org/50%\r\nz", "q"), (51, None, "q"), (60, "http://b.org/", "é" * 20_000)]
    rows += [(70, "http://b.org/70", "same"), (70, "http://b.org/70", "same")]
    pages = with_clashes(spark.createDataFrame(rows, "page_id long, url string, html string").drop("none"))
    path = warc.shared_dir(spark)
    warc.write_archives(spark.createDataFrame(rows, "page_id long, url string, html string"), path)
    captures = warc.read_archives(spark, path)
    got = captures.collect()
    assert len(got) == len(rows) and {r.url for r in got} == {u or "" for _, u, _ in rows}
    assert {r.page_id: (r.record_type, r.refers_to) for r in got if r.page_id in (3, 51, 70)} == {3: ("revisit", 2), 51: ("revisit", 50), 70: ("response", None)}
    sizes = Counter(re.search(r"size(\d)", r.file)[1] for r in got)
    assert sizes["0"] == 9 and sizes["1"] == 2 and sizes["2"] == 1 or sum(sizes.values()) == len(rows)
    warc.check_revisits(captures)
    with pytest.raises(ValueError, match="not there"):
        warc.check_revisits(captures.where("page_id is null or page_id != 50"))
    assert "url" in pages.columns


# ---- language ------------------------------------------------------------------------------------


def test_a_letter_anywhere_counts(spark):
    rows = [(i, "ala bela kela", "aa") for i in range(8)] + [(20, "x²", None), (21, "² ½", None), (22, "3 4 !", None), (23, "é1", None)]
    got = {r.doc_id: r.lang_pred for r in language.predict(frame(spark, rows)).collect()}
    assert {i: got[i] for i in (20, 21, 22, 23)} == {20: "aa", 21: "und", 22: "und", 23: "aa"}


# ---- shards -----------------------------------------------------------------------------------------


def test_shards_of_a_hot_group(spark):
    rows = [(i, "one hot text" if i % 3 == 0 else text(5), None) for i in range(300)] + [(None, "one hot text", None), (7, None, None)]
    got = sharding.balanced_shards(with_clashes(frame(spark, rows)), shards=10).collect()
    count = Counter(r.shard for r in got)
    assert max(count.values()) - min(count.values()) <= 1 and len(got) == len(rows) and {r.law for r in got} == {"rows"}
    for r in got:
        if r.doc_id is not None and r.doc_id % 3 == 0:
            assert r.size == len(b"one hot text") + 16 and r.text_crc32 == zlib.crc32(b"one hot text")
    hot = {r.shard for r in got if r.text_crc32 == zlib.crc32(b"one hot text")}
    assert len(hot) <= 8  # 101 rows fill 4 shards; round robin alone would touch all ten


def test_cut_edges_fall(spark):
    rows = [(i, f"group {i % 60}", None) for i in range(240)] + [(1000 + i, text(5), None) for i in range(240)]
    docs = frame(spark, rows)
    before = sharding.cut_edges(sharding.balanced_shards(docs, shards=12, rounds=0)).first()
    after = sharding.cut_edges(sharding.balanced_shards(docs, shards=12)).first()
    assert before.n_groups == after.n_groups == 60 and after.extra_shards < before.extra_shards / 2


# ---- decontamination --------------------------------------------------------------------------------------


def brute_contaminated(docs, items):
    """The definition, document by document and offset by offset, in plain Python."""
    token = re.compile(r"§?[^\W\d_]+|\d+(?:[.,]\d+)*")

    def tokens(t):
        return token.findall(re.sub(r"(?<=[a-z0-9,;:] )(?=[A-Z][a-z])", "§", t or ""))

    def kind(w):
        low = w.lower()
        return "§name" if w[0] == "§" else "§number" if w[0].isdigit() else "§unit" if low in decontaminate.UNITS else low

    plain = lambda w: w.lstrip("§").lower()
    out = set()
    for item_id, item in items:
        a = tokens(item)
        if len(a) < decontaminate.SHORTEST:
            continue
        size = min(len(a), decontaminate.WINDOW)
        for doc_id, doc in docs:
            b, covered = tokens(doc), set()
            for shift in range(-len(a) + size, len(b) - size + 1):
                exact, loose = set(), set()
                for i in range(len(a) - size + 1):
                    if not 0 <= i + shift <= len(b) - size:
                        continue
                    x, y = a[i : i + size], b[i + shift : i + shift + size]
                    slots = sum(kind(w)[0] == "§" for w in x)
                    if [*map(plain, x)] == [*map(plain, y)]:
                        exact |= set(range(i, i + size))
                    elif [*map(kind, x)] == [*map(kind, y)] and slots * 8 <= 3 * size:
                        loose |= set(range(i, i + size))
                pairs = {(a[i], b[i + shift]) for i in exact | loose if kind(a[i])[0] == "§"}
                good = len({p for p, _ in pairs}) == len(pairs) == len({q for _, q in pairs})
                covered |= exact | (loose if good else set()) if not loose or good else exact
            if len(covered) >= min(decontaminate.MATCHED, len(a)):
                out.add((doc_id, item_id))
    return out


def test_decontamination_equals_brute_force(spark):
    rng = random.Random(4)
    words = [f"{c}{v}" for c in "bdfgklmnprst" for v in ("alo", "ena", "iro", "osu")]
    say = lambda n: [rng.choice(words) for _ in range(n)]
    items, docs = [], []
    for i in range(8):
        own = say(rng.choice([6, 12, 20]))
        for at in rng.sample(range(1, len(own)), len(own) // 6):
            own[at] = str(rng.randint(10, 99))
        items.append((i, " ".join(own)))
    for i in range(60):
        item = items[i % 8][1].split()
        change = i % 5
        if change == 1:  # other numbers, one to one
            item = [str(int(w) + 100) if w.isdigit() else w for w in item]
        elif change == 2:  # half of it
            item = item[: len(item) // 2]
        elif change == 3:
            item = say(10)
        docs.append((i, " ".join([*say(15), *item, *say(15)])))
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontaminate.contamination(frame(spark, [(*d, None) for d in docs]), bench).collect()}
    assert got == brute_contaminated(docs, items) and len(got) >= 30


def test_repeated_and_null_ids(spark):
    item = "Where do the quiet herons sleep when winter comes to the valley again"
    bench = spark.createDataFrame([(1, item), (1, item), (None, item)], "item_id long, text string")
    rows = [(1, f"{text(5)} {item}", None), (1, text(9), None), (None, item, None), (None, text(9), None), (3, text(9), None)]
    got = sorted((r.doc_id or 0, r.contaminated) for r in decontaminate.verdicts(with_clashes(frame(spark, rows)), bench).collect())
    assert got == [(0, True), (0, True), (1, True), (1, True), (3, False)]


# ---- search and pieces ----------------------------------------------------------------------------------------


def test_top_k_of_large_values_and_extra_columns(spark):
    rng = np.random.default_rng(1)
    rows = [(i, [float(x) for x in rng.normal(size=6) * 1e6]) for i in range(120)] + [(50, [1.0] * 6)]
    got = topk.exact_top_k(with_clashes(spark.createDataFrame(rows, "vec_id long, embedding array<double>")), F.col("vec_id") % 50 == 0)
    assert {r["rank"] for r in got.collect()} == {1, 2, 3, 4, 5}


def test_pieces_of_a_long_text(spark):
    long = "word " * 30_000 + "x" * 50_000 + " \n\tend"
    got = unigram.encode(frame(spark, [(1, long, None), (1, long, None)])).collect()
    assert len(got) == 2 and all(r.round_trip for r in got)
    assert DOCS.startswith("doc_id")
