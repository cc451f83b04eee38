"""The corpus operators against brute force and on hard cases: nulls, empty and long texts, ties, repeated rows, clashing names."""

import collections
import re
import zlib

import numpy as np
import pytest
from orthant.llm import classifiers, embeddings, html_text, jaccard, language, licenses, linear, mixing, packing, quality_rules
from pyspark.sql import functions as F

W = re.compile("[^\x20\x09-\x0d]+")
LOWER = {c: c + 32 for c in range(65, 91)}
DOCS = "doc_id long, text string, lang string, source string, n_chars long, kept string, n_words string, row string, k0 string"


def hard_rows():
    base = "one two three four five six seven eight nine ten eleven twelve"
    texts = [None, "", " \n\t ", "a", base, base, "word " * 30000, "Ünïcödé ßtraße 日本語 🙂🙂 x", "# * $ % & | < >", base + "\n" + base, "!!! ??? 123"]
    rows = [(i, t, "en" if i % 3 else None, "s" if i % 2 else None, len(t or ""), "x", "y", "z", "k") for i, t in enumerate(texts)]
    return rows + [rows[4], (None, base, "en", "s", 1, "x", "y", "z", "k"), (None, None, None, None, None, None, None, None, None)]


@pytest.fixture(scope="module")
def hard(spark):
    return spark.createDataFrame(hard_rows(), DOCS)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(4, 1, 0), (5, 1, 0), (6, 0, 1), (9, 1, 0), (8, 0, 1), (7, None, None), (None, 1, 1), (4, 1, 0)], "doc_id long, quality int, toxic int")


def size(t):
    return len(W.findall(t or ""))


def test_mix_targets_and_words(docs):
    got = mixing.taken_words(docs).toPandas()
    assert (got["taken"] <= 2 * got["size"]).all() and (got["taken"] % got["size"].clip(lower=1) == 0).all()
    text = {r.doc_id: (r.text, r.source) for r in docs.collect()}
    assert all(size(text[r.doc_id][0]) == r.size for r in got.itertuples())
    got["source"] = [text[i][1] for i in got["doc_id"]]
    sizes = got.groupby("source")["size"].sum().sort_index()
    weights = dict(zip(sizes.index, [(3, 1, 2)[i % 3] for i in range(len(sizes))], strict=True))
    want, capped, left = {}, set(), 1.5 * sizes.sum()
    while True:  # deal, cap, deal the rest again
        free = [s for s in sizes.index if s not in capped]
        rest = left - sum(2 * sizes[s] for s in capped)
        share = {s: rest * weights[s] / sum(weights[x] for x in free) for s in free}
        over = [s for s in free if share[s] > 2 * sizes[s]]
        if not over:
            want = share | {s: 2.0 * sizes[s] for s in capped}
            break
        capped |= set(over)
    by = got.groupby("source").agg(target=("target", "first"), taken=("taken", "sum"))
    assert np.allclose(by["target"], [want[s] for s in by.index])
    assert abs(by["taken"].sum() / by["target"].sum() - 1) < 0.03


def test_mix_reruns_and_hard_rows(hard, empty):
    a, b = (sorted(map(repr, mixing.taken_words(x).collect())) for x in (hard, hard.repartition(5)))
    assert a == b and len(a) == hard.count()
    assert mixing.taken_words(empty).count() == 0
    mixed = mixing.mixed_documents(hard)
    assert mixed.columns == hard.columns
    assert mixing.mixed_documents(empty).count() == 0


def test_dual_coordinate_descent_separates():
    order = np.random.default_rng(0)
    x = order.standard_normal((200, 5))
    y = np.sign(x @ np.array([2.0, -1, 0.5, 0, 0]) + 0.3)
    w, b = linear.dual_coordinate_descent([np.arange(5)] * 200, list(x), y, 5, np.full(200, 10.0), 60)
    assert (np.sign(x @ w + b) == y).mean() > 0.97


@pytest.mark.parametrize("kind", ["quality", "toxic"])
def test_classifiers_held_out(spark, kind):
    sf = "/root/testdata/sf0.01"
    docs, marks = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    run, modulus, rest = (classifiers.quality_scores, 4, 2) if kind == "quality" else (classifiers.toxicity_scores, 3, 1)
    got = run(docs, marks).toPandas()
    assert len(got) == 1000 and got["score"].between(0, 1).all() and ((got["score"] >= 0.7) == (got["predicted"] == 1)).all()
    assert all(h == (zlib.crc32(str(i).encode()) % modulus == rest) for i, h in zip(got["doc_id"], got["held_out"], strict=True))
    held = got[got["held_out"]].merge(marks.toPandas(), on="doc_id")
    assert (held["predicted"] == held[kind]).mean() > (0.93 if kind == "quality" else 0.88)


def test_classifiers_ignore_held_out_labels(docs, spark, sf):
    marks = spark.read.parquet(f"{sf}/labels.parquet")
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2
    other = marks.withColumn("quality", F.when(held, 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = (sorted(map(tuple, classifiers.quality_scores(docs, m).collect())) for m in (marks, other))
    assert a == b


def test_classifiers_hard_rows(hard, empty, labels):
    for run in (classifiers.quality_scores, classifiers.toxicity_scores):
        got = run(hard, labels).toPandas()
        assert len(got) == hard.count() and got["score"].notna().all()
        assert run(empty, labels).count() == 0
        assert run(hard, labels.limit(0)).toPandas()["score"].nunique() == 1
    assert classifiers.good_documents(hard, hard, labels).columns == hard.columns


def brute_counts(t):
    t = t or ""
    w = W.findall(t)
    lines = [x for x in t.split("\n") if W.search(x)]
    grams = collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    cover = {p for i in range(len(w) - 4) if grams[tuple(w[i : i + 5])] > 1 for p in range(i, i + 5)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(cover)


def test_quality_rules(docs, hard, empty):
    for frame in (docs, hard):
        texts = collections.defaultdict(list)
        for r in frame.collect():
            texts[r.doc_id].append(brute_counts(r.text))
        got = quality_rules.verdicts(frame).collect()
        assert len(got) == frame.count()
        for r in got:
            assert tuple(r)[1:6] in texts[r.doc_id]
            n, rep = r.n_words, r.n_repeat_words
            assert r.base_failed == (n < 10 or 100 * rep > 20 * n) and not (r.base_failed and r.kept)
    assert quality_rules.verdicts(empty).count() == 0
    assert quality_rules.kept_documents(hard).columns == hard.columns
    assert quality_rules.kept_documents(empty).count() == 0


def test_quality_cutoff_lets_single_statistics_reject(spark):
    assert abs(quality_rules.CUTOFF - 22.458) < 0.001
    order = np.random.default_rng(2)
    word = lambda: "".join(order.choice(list("abcdefghij"), order.integers(2, 9)))
    text = lambda n: " ".join(word() for _ in range(n))
    rows = [(i, text(order.integers(100, 300)) + ".", "en", "s") for i in range(300)]
    rows += [(1000 + i, text(150) + "\nsame" * 21, "en", "s") for i in range(5)]
    rows += [(2000 + i, text(16).upper(), "en", "s") for i in range(5)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = {r.doc_id: r for r in quality_rules.verdicts(frame).collect()}
    assert not any(r.base_failed for r in got.values())
    assert all(r.kept == (i < 1000) for i, r in got.items())
    assert [tuple(r) for r in quality_rules.rejections(frame).collect()] == [("en", "s", 310, 0, 10)]


def test_covariance_determinant_finds_planted_outliers(spark):
    order = np.random.default_rng(1)
    word = lambda: "".join(order.choice(list("abcdefghij"), order.integers(2, 9)))
    rows = [(i, " ".join(word() for _ in range(order.integers(40, 300))) + ".", "en", "s", 0) for i in range(400)]
    rows += [(1000 + i, " ".join(word() + "###$$" for _ in range(120)), "en", "s", 0) for i in range(60)]
    got = quality_rules.verdicts(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")).toPandas()
    clean = got["doc_id"] < 1000
    assert got[clean]["kept"].all() and not got[~clean]["kept"].any()


def test_license_automata():
    a = licenses.compile_template("licensed under {? the ?} foo license version {= 1-2 =} end")
    yes = ["licensed under foo license version 2 end", "x licensed under the foo license version 2 0 end y"]
    no = ["licensed under foo license version end", "licensed under a foo license version 2 end", "licensed under foo license version 1 2 3 end"]
    assert all(a.accepts(t.split()) for t in yes) and not any(a.accepts(t.split()) for t in no)
    for name, markup in licenses.TEMPLATES.items():
        automaton = licenses.compile_template(markup)
        plain = re.sub(r"\{=[^=]*=\}", "filler", re.sub(r"\{\?|\?\}", "", markup)).split()
        assert automaton.accepts(["before", *plain, "after"]), name
        must = re.sub(r"\{=[^=]*=\}", "filler", re.sub(r"\{\?(?:[^{}]|\{[^?][^{}]*\}|\{\?[^{}]*\?\})*\?\}", "", markup)).split()
        assert automaton.accepts(must), name
        assert not automaton.accepts(must[:-2]) and not automaton.accepts([*must[: len(must) // 2], "zzz", "qqq", *must[len(must) // 2 :]])


def test_license_scan(docs, hard, empty):
    word = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    for frame in (docs, hard):
        text = collections.defaultdict(list)
        for r in frame.collect():
            words = word.findall((r.text or "").translate(LOWER))
            starts, found = [], set()
            for phrase, label in licenses.PHRASES.items():
                p = phrase.split()
                hits = [i for i in range(len(words)) if words[i : i + len(p)] == p]
                starts += hits
                found |= {label} if hits else set()
            text[r.doc_id].append((len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(found))))
        for r in licenses.scan(frame).collect():
            assert tuple(r)[1:6] in text[r.doc_id] and set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(","))
    assert licenses.scan(empty).count() == 0


def test_packing_round_trip(docs, hard, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for frame in (docs, hard):
        texts = collections.Counter()
        for r in frame.collect():
            ids = np.array([*tokenizer.encode(r.text or "", add_special_tokens=False).ids, 1], "<u4")
            texts[(r.doc_id, ids.tobytes())] += 1
        pieces = packing.packed_public(frame).toPandas().sort_values(["sequence_id", "offset"])
        by = pieces.groupby("sequence_id")["length"]
        assert (pieces["offset"] == by.cumsum() - pieces["length"]).all()
        totals = by.sum()
        assert (totals.iloc[:-1] == packing.LENGTH).all() and totals.iloc[-1] <= packing.LENGTH
        whole, open_docs = collections.Counter(), {}
        for r in pieces.itertuples():  # a document's pieces stand one after another in the stream
            assert zlib.crc32(r.ids) == r.ids_crc32 and len(r.ids) == 4 * r.length
            open_docs = {} if r.start == 0 else open_docs
            open_docs["ids"] = (b"" if r.start == 0 else open_docs["ids"]) + bytes(r.ids)
            if r.start + r.length == r.doc_tokens:
                whole[(None if r.doc_id != r.doc_id else int(r.doc_id), open_docs["ids"])] += 1
        assert whole == texts
    assert packing.packed_public(empty).count() == 0


def test_packing_windows_follow_shares(spark):
    rows = [(i, i, "a" if i % 4 else "b", 50 + (i * 37) % 200) for i in range(4000)]
    docs = spark.createDataFrame(rows, "rid long, doc_id long, source string, doc_tokens long")
    placed = packing.positions(docs, 16384).join(docs, "rid").toPandas()
    total = placed.groupby("source")["doc_tokens"].sum()
    for _, w in list(placed.groupby("window"))[:-1]:
        share = w.groupby("source")["doc_tokens"].sum()
        assert np.abs(share / share.sum() - total / total.sum()).max() < 0.04
    assert sorted(placed["position"]) == list(np.cumsum([0, *placed.sort_values("position")["doc_tokens"]])[:-1])


def shingles(t):
    w = W.findall((t or "").translate(LOWER))
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def brute_components(rows):
    sets = collections.defaultdict(list)
    for i, t in rows:
        if i is not None:
            sets[i].append(shingles(t))
    ids, parent = sorted(sets), {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    flat = [(i, s) for i in ids for s in sets[i] if s]
    for n, (i, a) in enumerate(flat):
        for j, b in flat[:n]:
            if find(i) != find(j):
                shared = len(a & b)
                if 100 * shared >= 75 * (len(a) + len(b) - shared):
                    x, y = find(i), find(j)
                    parent[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def check_components(frame):
    rows = [(r.doc_id, r.text) for r in frame.collect()]
    want, sizes = brute_components(rows), collections.Counter((i, len(shingles(t))) for i, t in rows)
    got = jaccard.join_components(frame).collect()
    assert collections.Counter((r.doc_id, r.n_shingles) for r in got) == sizes
    assert all(r.component_id == (None if r.doc_id is None else want[r.doc_id]) for r in got)


def test_jaccard_join_on_tables_and_hard_rows(docs, hard, empty):
    check_components(docs)
    check_components(hard)
    assert jaccard.join_components(empty).count() == 0
    assert jaccard.representatives(hard).columns == hard.columns


def test_jaccard_join_near_copies_and_passages(spark):
    """Many near copies about the bar, texts that are mostly one passage, and small sets."""
    order = np.random.default_rng(3)
    words = [f"w{i}" for i in range(4000)]
    pick = lambda n: [words[i] for i in order.integers(0, len(words), n)]
    rows, base, passage = [], pick(120), pick(50)
    for i in range(150):
        t = list(base)
        for p in order.choice(len(t), order.integers(0, 6), replace=False):
            t[p] = "z" + words[order.integers(0, len(words))]
        rows.append((i, " ".join(t)))
    rows += [(200 + i, " ".join([*pick(order.integers(1, 12)), *passage, *pick(order.integers(1, 9))])) for i in range(120)]
    rows += [(400 + i, " ".join(pick(5)[:1] * 1 + base[: order.integers(4, 9)])) for i in range(60)]
    rows += [(500 + i, " ".join(pick(60))) for i in range(60)] + [(600 + i, rows[i][1]) for i in range(0, 150, 7)]
    check_components(spark.createDataFrame(rows, "doc_id long, text string").repartition(6))


def test_prefix_keys_share_when_similar():
    """Whatever is called frequent, two sets over the bar share a key whose limit allows the overlap."""
    order = np.random.default_rng(5)
    for trial in range(400):
        n = int(order.integers(2, 90))
        common = order.integers(0, 1 << 62, n).astype(np.uint64)
        extra = lambda m: order.integers(0, 1 << 62, m).astype(np.uint64)
        a, b = (np.unique(np.concatenate([common, extra(order.integers(0, 1 + n // 5))])) for _ in range(2))
        shared = len(np.intersect1d(a, b))
        if 100 * shared < 75 * (len(a) + len(b) - shared):
            continue
        share = order.random()
        frequent = lambda u, s=share: (u % np.uint64(1000)) < np.uint64(1000 * s)
        (ka, la, _), (kb, lb, _) = (jaccard.prefix_keys(u, frequent(u)) for u in (a, b))
        need = jaccard._need(len(a), len(b))
        left, right = ({k: max(l[ks == k]) for k in set(ks.tolist())} for ks, l in ((ka, la), (kb, lb)))
        assert any(min(left[k], right[k]) >= need for k in set(left) & set(right)) or np.array_equal(a, b), trial


def test_embeddings(spark):
    order = np.random.default_rng(2)
    base = order.standard_normal((40, 24))
    vectors = np.concatenate([base, base[:20] + 0.08 * order.standard_normal((20, 24)), base[:5], base[5:8] * 3, base[0] + 0.12 * order.standard_normal((80, 24))]).astype(np.float32)
    rows = [(i, v.tolist(), i % 2 if i < 40 else (i % 40) % 2 if i < 68 else 0) for i, v in enumerate(vectors)]
    hard = [(900, None, 1), (901, [0.0] * 24, 1), (902, [float("nan")] * 24, 1), (903, base[0].tolist(), None), (904, [None] * 24, 1), (905, [], 1), (None, base[0].tolist(), 0), (906, [1.0, 2.0], 0), (3, rows[3][1], rows[3][2])]
    frame = spark.createDataFrame(rows + hard, "vec_id long, embedding array<float>, label int")
    got = embeddings.near_duplicates(frame).toPandas()
    assert len(got) == len(rows) + len(hard)
    all_rows = [*rows, hard[-1]]
    x = np.array([r[1] for r in all_rows], float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    label = np.array([r[2] for r in all_rows])
    link = (x @ x.T >= 0.93) & (label[:, None] == label[None, :])
    np.fill_diagonal(link, False)
    ids, want = np.array([r[0] for r in all_rows]), {}
    root = np.arange(len(ids))
    for _ in range(len(ids)):
        new = np.array([min(root[i], *(root[j] for j in np.flatnonzero(link[i]))) if link[i].any() else root[i] for i in range(len(ids))])
        if (new == root).all():
            break
        root = new
    for i, r in enumerate(root):
        want.setdefault(ids[i], set()).add((int(link[i].sum()), ids[r]))
    sound = got[got["vec_id"].isin(ids)]
    exact = [(r.n_links, r.component_id) in want[r.vec_id] for r in sound.itertuples()]
    assert np.mean(exact) > 0.98
    rest = got[got["vec_id"] >= 900]
    assert (rest["n_links"] == 0).all() and (rest["component_id"] == rest["vec_id"]).all()
    assert embeddings.near_duplicates(frame.limit(0)).count() == 0


def test_multi_sequence_order():
    order = np.random.default_rng(4)
    grid = embeddings.Grid(order.standard_normal((300, 8)), 9)
    x = order.standard_normal((20, 8))
    a, b = grid.distances(x)
    for i, row in enumerate(grid.visits(x, 25)):
        sums = (a[i][:, None] + b[i][None, :]).ravel()
        assert np.allclose(np.sort(sums)[:25], sums[row]) and (grid.rank(x[i : i + 1], row[:1]) == 0).all()


def test_visits_suit_pairs_beside_a_large_group():
    """One group with 300 queries of 1000 links each at rank 0, and 60 pairs at ranks of up to 700."""
    group = np.append(np.zeros(300, int), np.arange(1, 61))
    rank, n = np.append(np.zeros(300, int), np.linspace(1, 700, 60).astype(int)), np.append(np.full(300, 1000), np.ones(60, int))
    count = embeddings.least_count(group, np.arange(360), rank, n)
    assert (rank[300:] < count).mean() >= 0.98 and count > 512


def test_links_of_rare_pairs_are_found(spark):
    """A hundred pairs at cosine 0.935 among many others, and one tight group of a third of all vectors."""
    order = np.random.default_rng(11)
    norm = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    rest = norm(order.standard_normal((4000, 16)))
    u = order.standard_normal((100, 16))
    u = norm(u - (u * rest[:100]).sum(1)[:, None] * rest[:100])
    group = norm(rest[3999] + 0.004 * order.standard_normal((2000, 16)))
    x = np.concatenate([rest, 0.935 * rest[:100] + (1 - 0.935**2) ** 0.5 * u, group]).astype(np.float32)
    frame = spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(x)], "vec_id long, embedding array<float>, label int")
    got = {r.vec_id: r.n_links for r in embeddings.near_duplicates(frame).collect()}
    y = norm(x.astype(float))
    want = (y @ y.T >= 0.93).sum(1) - 1
    pairs = [*range(100), *range(4000, 4100)]
    assert sum(got[i] for i in pairs) >= 0.98 * sum(want[i] for i in pairs) and all(got[i] <= want[i] for i in got)


def test_html_texts(spark, sf):
    pages = [
        (1, "http://h.x/1", "<html><head><title>t</title><script>var a='</p>';</script></head><body><header>top</header><nav><ul><li>menu</li></ul></nav><article><h1>Title &amp; more</h1><p>One  two<br>three<p>Four<div class='ad'>buy</div><div class='comments'><p>nice</p></div></article><aside>side</aside><footer>f</footer>"),
        (2, None, None), (3, "x", ""), (4, "http://h.x/4", "<main><p>a < b</p><!-- c --><ul><li>i<li>j</ul></main>"), (5, "http://h.x/5", "<p>unclosed <b>bold"),
        (6, "http://b.x/1", "<div>same words on every page of this very host</div><p>first own text</p>"),
        (7, "http://b.x/2", "<div>same words on every page of this very host</div><p>second own text</p>"),
        (8, "http://c.x/1", "<div>same words on every page of this very host</div>"),
        (9, "http://h.x/9", "<article><nav>open menu<p>lost</article><p>after"),
    ]
    frame = spark.createDataFrame([(*p, "clash") for p in pages], "page_id long, url string, html string, text string")
    got = {r.page_id: r.text for r in html_text.page_texts(frame).collect()}
    assert got == {1: "Title & more\nOne two three\nFour", 2: "", 3: "", 4: "a < b\ni\nj", 5: "unclosed bold", 6: "first own text", 7: "second own text", 8: "same words on every page of this very host", 9: "after"}
    assert html_text.page_texts(frame.limit(0)).count() == 0
    for r in html_text.page_texts(spark.read.parquet(f"{sf}/pages.parquet")).collect():
        assert r.n_chars == len(r.text) and r.text


def test_furniture_names_leave_articles_whole():
    page = (
        '<body class="page has-sidebar"><div class="main-menu">menu</div><article class="post comments-open" id="social"><h2 id="social-impact">Impact</h2>'
        '<section id="related-work"><p class="side-effects">effects</p></section><div class="entry-header">title</div><h3 class="alert">heading</h3>'
        '<div class="clearfix related-posts">more</div><div class="ad">buy</div><div class="post-comments">nice</div><ul class="share-buttons"><li>tweet</ul><h4 hidden>gone</h4></article></body>'
    )
    assert html_text.blocks(page)[0] == ["Impact", "effects", "title", "heading"]
    assert html_text.blocks('<body class="no-sidebar"><main id="content-nav"><p>kept</p></main></body>')[0] == ["kept"]


def test_equal_pages_of_a_host_are_one_page(spark):
    body = "<div>a notice that stands on every page of this host</div><p>{}</p>"
    pages = [(i, "http://d.x/" + str(i), body.format(t)) for i, t in ((1, "one text crawled twice under two ids"), (2, "one text crawled twice under two ids"), (3, "another text"))]
    got = {r.page_id: r.text for r in html_text.page_texts(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert got == {1: "one text crawled twice under two ids", 2: "one text crawled twice under two ids", 3: "another text"}


def test_pages_with_an_article_take_part_in_their_hosts_runs(spark):
    notice = "a notice that stands on every page of this host"
    pages = [
        (1, "http://e.x/1", f"<div>{notice}</div><article><h1>One</h1><p>{notice}</p></article><p>one line of its own</p>"),
        (2, "http://e.x/2", f"<div>{notice}</div><p>the page without an article</p>"),
        (3, "http://e.x/3", f"<main><h1>Three</h1><article>words</article></main><div>{notice} by one of them</div>"),
        (4, "http://f.x/4", f"<article>four</article><div>{notice}</div>"),
    ]
    got = {r.page_id: r.text for r in html_text.page_texts(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert got == {1: f"One\n{notice}\none line of its own", 2: "the page without an article", 3: "Three\nwords\nby one of them", 4: f"four\n{notice}"}


def test_the_bitmap_has_all_windows_of_two_pages_and_few_others(spark):
    own = lambda i, n: " ".join(f"p{i}w{j}" for j in range(n))
    text = [own(i, 300) + " " + own("all", 20 * (i % 2)) + " " + own("twice", 9) * 2 for i in range(40)]
    frame = spark.createDataFrame([(i, i % 4 // 2, i, t) for i, t in enumerate(text)], "uid long, host long, page long, text string").repartition(7)
    bitmap, buckets, bits = html_text._met_twice(frame, 8)
    got, want = 0, 0
    batch = frame.toArrow().to_batches()[0]
    for _, keys, _, _, _ in html_text._windows(batch, 8):
        bucket, _, bit = html_text._slots(keys, buckets, bits)
        met = (bitmap[bucket, bit >> 3] >> (7 - (bit & 7)).astype(np.uint8)) & 1 > 0
        _, at, n = np.unique(keys, return_inverse=True, return_counts=True)
        assert met[n[at] > 1].all()
        got, want = got + met.sum(), want + (n[at] > 1).sum()
    assert 0 < want <= got < 1.05 * want + 50


@pytest.mark.parametrize("share", [1, 7, 50_000])
def test_sorted_suffixes_give_lengths_and_cover_of_repeated_runs(spark, share):
    order = np.random.default_rng(3)
    passages = [" ".join(f"p{k}w{i}" for i in range(n)) for k, n in enumerate((8, 11, 37, 90))] + ["z " * 40]
    words = []
    for _ in range(14):
        parts = []
        for _ in range(5):
            parts += passages[order.integers(len(passages))].split() + [f"own{order.integers(10**6)}" for _ in range(order.integers(1, 9))]
        words.append(parts)
    words.append(list(words[0]))
    hosts = ["a" if i % 3 else "b" for i in range(14)] + ["b"]
    frame = spark.createDataFrame([(i, hosts[i], " ".join(w)) for i, w in enumerate(words)], "uid long, host string, text string")

    def common(a, b):
        n = 0
        while n < min(len(a), len(b)) and a[n] == b[n]:
            n += 1
        return n

    longest = {}
    for i, w in enumerate(words):
        others = [v for j, v in enumerate(words) if hosts[j] == hosts[i] and v != w]
        for p in range(len(w)):
            n = max((common(w[p:], v[q:]) for v in others for q in range(len(v))), default=0)
            if n >= 8:
                longest[i, p] = n
    got = {(r.uid, r.at): r.length for r in html_text.repeated_runs(frame, share=share).collect()}
    assert got.keys() == longest.keys() and all(8 <= got[k] <= longest[k] for k in got)
    if share > len(got):
        assert all(2 * got[k] > longest[k] for k in got)
    cover = lambda runs: {(i, x) for (i, p), n in runs.items() for x in range(p, p + n)}
    assert cover(got) == cover(longest)


def test_language_learns_from_late_words_and_every_label(spark):
    order = np.random.default_rng(4)
    make = lambda letters: ["".join(order.choice(list(letters), 6)) for _ in range(60)]
    vocabulary, filler = {"aa": make("abcdefgh"), "bb": make("stuvwxyz")}, make("ijklmnop")
    text = lambda words, n: " ".join(order.choice(words, n))
    rows = [(i, text(filler, 450) + " " + text(vocabulary[k], 600), k) for i, k in enumerate(["aa", "bb"] * 40)]
    rows += [(1000 + i, text(vocabulary[k], 30), None) for i, k in enumerate(["aa", "bb"] * 20)]
    got = {r.doc_id: r.lang_pred for r in language.language_predictions(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert all(got[1000 + i] == k for i, k in enumerate(["aa", "bb"] * 20))
    many = spark.createDataFrame([(i, f"word{i}", f"l{i}") for i in range(400)], "doc_id long, text string, lang string")
    with pytest.raises(ValueError, match="languages"):
        language.language_predictions(many)


def test_language(spark, hard, empty):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = language.language_predictions(docs).join(docs.select("doc_id", "lang"), "doc_id").toPandas()
    held = got[got["held_out"]]
    assert (held["lang"] == held["lang_pred"]).mean() > 0.97 and got["score"].between(0, 1).all()
    rows = language.language_predictions(hard).toPandas()
    assert len(rows) == hard.count() and (rows[rows["doc_id"].isin([0, 1, 2, 10])]["lang_pred"] == "und").all()
    assert language.language_predictions(empty).count() == 0


def test_forward_backward_against_enumeration():
    import itertools

    order = np.random.default_rng(6)
    scores, jump, prior = order.standard_normal((1, 5, 3)), order.standard_normal((3, 3)), order.standard_normal(3)
    gamma, pairs, log_z = language.posteriors(scores, jump, prior, np.array([4]))
    total, want, both = 0.0, np.zeros((5, 3)), np.zeros((3, 3))
    for path in itertools.product(range(3), repeat=4):
        p = np.exp(prior[path[0]] + sum(scores[0, i, y] for i, y in enumerate(path)) + sum(jump[a, b] for a, b in zip(path, path[1:], strict=False)))
        total += p
        for i, y in enumerate(path):
            want[i, y] += p
        for a, b in zip(path, path[1:], strict=False):
            both[a, b] += p
    assert np.allclose(gamma[0], want / total) and np.allclose(pairs, both / total) and np.isclose(log_z, np.log(total))


def test_components(spark):
    from orthant.llm.components import components

    order = np.random.default_rng(8)
    edges = [(i, i + 1) for i in range(60)] + [(100, int(x)) for x in order.integers(101, 160, 80)] + [(5, 5), (None, 3), (7, 6)]
    for one_task in (0, 10**6):
        got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long"), one_task=one_task).collect()}
        assert all(got[i] == 0 for i in range(61)) and all(r == 100 for n, r in got.items() if n >= 100)
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_pipeline_stages(spark, sf):
    import corpus_pipeline
    from orthant.llm.shared import materialize

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, [docs]
    for name, stage in corpus_pipeline.STAGES:
        seen.append(materialize(stage(spark, seen[-1], sf), "test-stage"))
        assert name == corpus_pipeline.STAGES[-1][0] or seen[-1].columns == columns
    kept = {r.doc_id for r in quality_rules.verdicts(docs).where("kept").collect()}
    assert {r.doc_id for r in seen[1].collect()} == kept
    want = brute_components([(r.doc_id, r.text) for r in seen[2].collect()])
    assert {r.doc_id for r in seen[3].collect()} == set(want.values())
    taken = {r.doc_id: r.taken // max(r.size, 1) for r in mixing.taken_words(seen[3]).collect()}
    assert collections.Counter(r.doc_id for r in seen[4].collect()) == collections.Counter({k: v for k, v in taken.items() if v})
    assert seen[5].agg(F.sum("length")).first()[0] == seen[5].where("start = 0").agg(F.sum("doc_tokens")).first()[0]


def test_mix_takes_as_many_repeated_rows_as_are_owed(spark):
    rows = [(7, "a b c", "s")] * 100 + [(None, "a b", "t")] * 100 + [(i, "w " * (i % 9 + 1), "u") for i in range(300)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(7)
    got = mixing.taken_words(frame).groupBy("source_size").agg(F.sum("taken").alias("taken"), F.first("target").alias("target"), F.max(F.col("taken") - 2 * F.col("size"))).collect()
    assert len(got) == 3 and all(abs(r["taken"] - r["target"]) <= 2 and r[3] <= 0 for r in got)
    assert mixing.mixed_documents(frame).groupBy("source").count().count() == 3


def test_representatives_hand_on_columns_of_any_name(spark):
    text = "one two three four five six seven eight nine ten"
    frame = spark.createDataFrame([(1, text, 1, 2, 3, 4), (2, text, 5, 6, 7, 8), (2, text, 9, 10, 11, 12), (3, "other words", 0, 0, 0, 0)], "doc_id long, text string, gone int, _twice int, _worded int, `a.b` int")
    got = jaccard.representatives(frame)
    assert got.columns == frame.columns
    assert sorted(tuple(r)[:1] + tuple(r)[2:] for r in got.collect()) == [(1, 1, 2, 3, 4), (3, 0, 0, 0, 0)]


def test_bitmaps_bound_the_overlap():
    order = np.random.default_rng(4)
    for _ in range(200):
        a = order.integers(0, 1 << 63, order.integers(1, 400)).astype(np.uint64)
        b = np.unique(np.concatenate([order.choice(a, order.integers(0, len(a) + 1), replace=False), order.integers(0, 1 << 63, order.integers(1, 400)).astype(np.uint64)]))
        a = np.unique(a)
        shared = len(np.intersect1d(a, b))
        most = jaccard.most_overlap(jaccard.bitmap(a), jaccard.bitmap(b), len(a), len(b))
        assert shared <= most
        if 0.75 <= len(a) / len(b) <= 4 / 3:  # sizes of possible partners
            assert most <= shared + 0.35 * min(len(a), len(b)) + 4


def test_very_frequent_pairs_leave_the_buckets(spark, monkeypatch):
    order, base = np.random.default_rng(6), [f"w{i}" for i in range(60)]
    rows = [(i, " ".join(w if order.random() > 0.015 else f"x{order.integers(1000)}" for w in base)) for i in range(150)]
    rows += [(200 + i, " ".join(f"y{order.integers(200)}" for _ in range(30))) for i in range(30)]
    plain = jaccard.frequent_buckets
    monkeypatch.setattr(jaccard, "frequent_buckets", lambda counts: plain(counts, hot=20))
    got = jaccard.join_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.doc_id: r.component_id for r in got} == brute_components(rows)


def test_packing_very_long_blanks(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    text = "a" + " " * 1_000_000 + "b"
    want = len(Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")).encode(text, add_special_tokens=False).ids) + 1
    got = packing.packed_digests(spark.createDataFrame([(1, text, "s")], "doc_id long, text string, source string")).collect()
    assert sum(r["length"] for r in got) == want == got[0]["doc_tokens"]


def test_embeddings_in_double_precision(spark):
    rows = [(1, [1e200, 2e200], 1), (2, [2e200, 4e200], 1), (3, [1e-200, 2e-200], 1), (4, [-1.0, 2.0], 1)]
    got = embeddings.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")).collect()
    assert {r.vec_id: (r.n_links, r.component_id) for r in got} == {1: (2, 1), 2: (2, 1), 3: (2, 1), 4: (0, 4)}


def test_texts_are_whole_chains():
    order = np.random.default_rng(3)
    n = np.array([0, 3, 200, 64, 65, 1, 700, 0, 129])
    bounds = np.append(0, np.cumsum(n))
    scores, jump, prior = order.normal(0, 2, (bounds[-1], 4)), order.normal(0, 1, (4, 4)), order.normal(0, 1, 4)
    got = language.chain_mass(scores, jump, prior, bounds)
    for i, m in enumerate(n):
        want = language.posteriors(scores[None, bounds[i] : bounds[i + 1]], jump, prior, np.array([m]))[0][0].sum(0) if m else np.zeros(4)
        assert np.allclose(got[i], want)


def test_furniture_without_end_tags_ends_where_html_says():
    page = '<article><h1>T</h1><p>before</p><ul><li class="related">a<ul><li>x</ul><li>b<li>c</ul><p>after<p class="share">s<p>real<dl><dt class="related">q<dd>d</dl></article>'
    assert html_text.blocks(page)[0] == ["T", "before", "b", "c", "after", "real", "d"]


def test_packing_rounds_are_those_of_the_deficit_loop(spark):
    """A loop over rounds that grants each queue its share and lets it overdraw by its last document."""
    order = np.random.default_rng(9)
    rows = [(i, i, "abc"[int(order.choice(3, p=[0.6, 0.3, 0.1]))], int(order.integers(1, 400))) for i in range(900)]
    docs = spark.createDataFrame(rows, "rid long, doc_id long, source string, doc_tokens long")
    window = 4096
    for targets in (None, {"a": 0.2, "b": 0.5, "c": 0.3}):
        placed = packing.positions(docs, window, targets).join(docs.select("rid", "source", "doc_tokens"), "rid").toPandas().sort_values("position")
        total = placed.groupby("source")["doc_tokens"].sum()
        share = {s: t / total.sum() for s, t in total.items()} if targets is None else targets
        queues = {s: list(g["doc_tokens"]) for s, g in placed.groupby("source")}
        sent, granted, n, got = dict.fromkeys(queues, 0), dict.fromkeys(queues, 0.0), 0, []
        while any(queues.values()):
            left, rest = float(window), {s for s in queues if granted[s] < total[s] - 1e-6}
            while rest and left > 1e-6:  # shares of dry queues go to the others
                open_share = sum(share[s] for s in rest)
                step = min(left / open_share, min((total[s] - granted[s]) / share[s] for s in rest))
                for s in rest:
                    granted[s] += step * share[s]
                left -= step * open_share
                rest = {s for s in rest if granted[s] < total[s] - 1e-6}
            for s in sorted(queues):
                while queues[s] and sent[s] < granted[s] - 1e-6:
                    sent[s] += queues[s][0]
                    got.append((n, s, queues[s].pop(0)))
            n += 1
        assert got == [(r.window, r.source, r.doc_tokens) for r in placed.itertuples()], targets
