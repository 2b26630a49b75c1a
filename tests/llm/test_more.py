"""The text operators against brute force: mixing, secrets, URLs, archives, search, extraction, classifier, decontamination."""

import base64
import hashlib
import itertools
import math
import random
import re
import time
import zlib
from collections import Counter

import numpy as np
import pytest
from test_llm import PATTERNS, WORDS, brute_components, brute_distance, clashing, docs_of

from roundjoin.llm import ann, common, decontaminate, html_text, licenses, mixing, ngram_join, quality, secrets, url_filter, warc


def offset_of(seed, key):
    return int(hashlib.md5(f"{seed}|{key}".encode()).hexdigest()[:7], 16) / float(1 << 28)


def test_mixing_by_a_plain_loop(spark):
    rng = random.Random(12)
    texts = [" ".join("x" * rng.choice((1, 2, 5, 5, 5, 40))) for _ in range(250)] + [None, "", "z " * 20_000, "same", "same"]
    ids = [*range(253), 7, 7]
    sources = [rng.choice(("b", "a", None, "é")) for _ in range(253)] + ["a", "a"]
    docs = docs_of(spark, texts, ids, sources)
    got = Counter(tuple(r) for r in mixing.plan_copies(docs, bucket_rows=20).collect())
    rows = [(s, len((t or "").split()), hashlib.md5(f"{i}|{t or ''}".encode()).hexdigest(), i) for i, t, s in zip(ids, texts, sources, strict=True)]
    names = sorted({s for s in sources if s is not None}) + [None]
    sizes = [sum(r[1] for r in rows if r[0] == s) for s in names]
    targets = mixing.share_out(sizes, [mixing.WEIGHTS[i % 3] for i in range(4)], 1.5 * sum(sizes), 2)
    want = Counter()
    for s, size, target in zip(names, sizes, targets, strict=True):
        u, rate, total = offset_of(mixing.SEED, "-" if s is None else "s" + s), target / size, 0
        own = sorted(r for r in rows if r[0] == s) if s is not None else sorted(r[1:] for r in rows if r[0] is None)
        for k, r in enumerate(own):
            copies = math.floor(u + rate * (k + 1)) - math.floor(u + rate * k)
            want[(r[-1], s, r[-3], size, target, copies)] += 1
            total += r[-3] * copies
        assert abs(total - target) <= own[-1][-3]
    assert got == want
    assert sum(mixing.emit(mixing.plan_copies(docs)).groupBy("doc_id").count().toPandas()["count"]) == sum(k[-1] * n for k, n in want.items())


def test_targets_by_rounds(spark):
    rng = random.Random(2)
    for n in (1, 2, 7, 40):
        sizes = [rng.choice((0, 1, 10, 1000, 100_000)) for _ in range(n)]
        totals = common.cut(spark.createDataFrame([(f"s{i:02d}", z) for i, z in enumerate(sizes)], "source string, source_size long"))
        got = [r.target for r in mixing.source_plan(totals, (3.0, 1.0, 2.0), 1.5, 2.0).orderBy("source").collect()]
        assert got == pytest.approx(mixing.share_out(sizes, [(3, 1, 2)[i % 3] for i in range(n)], 1.5 * sum(sizes), 2))


def test_spread_join(spark):
    rows = spark.createDataFrame([("hot" if i % 3 else f"k{i}", i) for i in range(900)] + [(None, -1)], "k string, i long")
    groups = common.cut(rows.where("k IS NOT NULL AND i <> 3").groupBy("k").count().selectExpr("k", "count AS n", "length(k) AS m"))
    inner = common.spread_join(rows, groups, "k", "i")
    assert inner.columns == ["k", "i", "m"] and inner.count() == 899
    left = common.spread_join(rows, groups, "k", "i", "left").collect()
    assert len(left) == 901 and sorted(r.i for r in left if r.m is None) == [-1, 3]


def brute_redaction(text, spans, mark="[SECRET]"):
    out, at = "", 0
    for a, b in sorted(spans):
        if a >= at:
            out += text[at:a] + mark
        at = max(at, b)
    return out + text[at:]


def test_many_secrets_in_one_text(spark):
    rng = random.Random(5)
    bits = ["token=abcdef12", "é", "x" * 9, "deadbeef" * 4, "AKIA" + "Q" * 16, "secret: " + "0a" * 14, "password = hunter2222,", "\n", "api_key=AKIA" + "Z" * 17]
    texts = [" ".join(rng.choice(bits) for _ in range(n)) for n in (1, 127, 128, 129, 700, 6000)] + ["token=abcdef12"] * 40
    docs = docs_of(spark, texts)
    started = time.time()
    found = {r.doc_id: r for r in secrets.find_secrets(docs).collect()}
    clean = {r.doc_id: r for r in secrets.redact_secrets(docs).collect()}
    assert time.time() - started < 60
    for i, t in enumerate(texts):
        spans = sorted((m.start(), k, n, m.end()) for k, (n, p, g, least) in enumerate(PATTERNS) for m in re.finditer(p, t) if len(m[g]) >= least)
        assert found[i].spans == ",".join(f"{n}:{a}:{b}" for a, _, n, b in spans)
        assert clean[i].text == brute_redaction(t, [(a, b) for a, _, _, b in spans]) and clean[i].n_chars == len(clean[i].text)


def test_archives_of_awkward_payloads(spark, tmp_path):
    ends = ["", "\r\n", "\r\n\r\n", "\r\n\r\n\r\n", "\r", "\n", "\r\n\r", "x\r\n\r\nWARC/1.1\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n"]
    html = [a + b for a in ends for b in ("", "é body")] + [a + b for a in ("", "y") for b in ends] * 2
    rows = [(i, f"http://h/{i}", h) for i, h in enumerate(html)] + [(3, "http://h/3", html[3]), (None, None, "only without an id"), (None, "u", html[5])]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    for compression, per_file in (("gzip", 5), ("none", 1000)):
        path = warc.write_archives(pages, str(tmp_path / compression), records_per_file=per_file, compression=compression)
        got = Counter(tuple(r) for r in warc.read_archives(spark, path).collect())
        first, want = {}, Counter()
        for i, _, h in rows:
            if i is not None:
                first[h] = min(i, first.get(h, i))
        for i, _, h in rows:
            own = first.get(h, i)
            digest = base64.b32encode(hashlib.sha1(h.encode()).digest()).decode()
            want[(i, len(h.encode()), digest, "response" if own == i else "revisit", None if own == i else own, True)] += 1
        assert got == want
    text = "".join(x.read_text(newline="") for x in (tmp_path / "none").glob("part-*"))
    assert text.count("WARC-Refers-To-Target-URI: http://h/") == text.count("WARC-Type: revisit") == text.count("WARC-Refers-To: <")
    large = warc.round_trip(pages, min_bytes=10**6)
    assert {r.record_type for r in large.collect()} == {"response"}


def test_viterbi_against_all_labelings():
    rng = random.Random(9)
    for _ in range(60):
        names = ["", *"abcd"]
        emit, move = (np.array([[rng.gauss(0, 2) for _ in range(2)] for _ in range(k)]) for k in (5, 2))
        model = html_text.ChainModel(names, emit, move)
        rows = [tuple(x for x in "abcd" if rng.random() < 0.5) for _ in range(rng.randint(1, 8))]

        def score(labels):
            return sum(emit[[names.index(f) for f in ("", *r)], y].sum() for r, y in zip(rows, labels, strict=True)) + sum(move[p, q] for p, q in itertools.pairwise(labels))

        assert score(model.decode(rows)) == pytest.approx(max(map(score, itertools.product((0, 1), repeat=len(rows)))))


def test_extraction_keeps_the_whole_article(spark):
    cases = {
        "<article><p class=it's>one two</p><p>three it's fine.</p></article>": "one two three it's fine.",
        "<article><h1>T</h1><table><tr><td>a b<td>c d</table><pre>x = 1\ny</pre></article>": "T a b c d x = 1 y",
        "<article><h1>Head</h1><div class='story-date-tags'><p>A paragraph of some words that is text.</p></div><p>More of it here.</p></article>": "Head A paragraph of some words that is text. More of it here.",
        "<article><h1>T</h1><dl><dt>term one<dd>what it means here.</dl><figure><img src=x><figcaption>A caption of it.</figcaption></figure><p>End of it.</article>": "T term one what it means here. A caption of it. End of it.",
        '<article><p title="a > b" data-x=\'">\'>Quoted signs are no tags.</p><p>And more text.</p></article>': "Quoted signs are no tags. And more text.",
        "<nav><a href=/>Home</a></nav><article><h1>Title of it</h1><p>Some text of the page.</p></article><footer>&copy; us</footer>": "Title of it Some text of the page.",
    }
    rows = [(i, "u", h) for i, h in enumerate(cases)] * 2 + [(99, None, "<div>" * 60_000 + "deep text"), (None, "u", None)]
    got = html_text.extract_main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    for i, want in enumerate(cases.values()):
        assert [r.text for r in got if r.page_id == i] == [want] * 2
    assert len(got) == len(rows) and next(r for r in got if r.page_id is None).text == ""


def test_parsing_takes_time_in_proportion():
    for page in ("<div>a ", "<span>a ", "<a href=x>a ", "<ul><li>a ", "<table><tr><td>a ", "<button>a ", "<object>a "):
        started = time.time()
        html_text.leaf_blocks(page * 20_000 + "<div>b</div>" * 20_000)
        assert time.time() - started < 10, page


def test_search_of_shards_with_parts_and_ties(spark, small):
    rng = np.random.default_rng(3)
    far = np.vstack([rng.normal(size=(30, 6)) + 1000 * rng.normal(size=6) for _ in range(12)])
    far[40:70] = far[40]
    rows = [(i, v.tolist()) for i, v in enumerate(far)] + [(0, far[0].tolist()), (1000, [1.0, 2.0]), (1001, [3.0, 4.0]), (1020, [5.0, 6.0]), (20, None)]
    got = ann.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), shard_rows=100, query_block=7).toPandas()
    hits = 0
    for q in range(0, 360, 20):
        s = far @ far[q]
        s[q] = -np.inf
        own = got[got.query_id == q].sort_values("rank")
        assert len(own) == 20 and own.vec_id.is_unique
        hits += sum(s[v] >= np.sort(s)[-20] for v in own.vec_id)
        assert [tuple(x) for x in own[["score", "vec_id"]].values] == sorted(map(tuple, own[["score", "vec_id"]].values), key=lambda x: (-x[0], x[1]))
    assert hits / 360 >= 0.9
    assert got[got.query_id.isin((1000, 1020))].groupby("query_id").vec_id.apply(list).to_dict() == {1000: [1020, 1001], 1020: [1001, 1000]}
    graph = np.full((50, 4), -1)
    shard = ann.Shard(far[:50], [[i] for i in range(50)], 4, 16, 1.2)
    shard.graph, shard.start = graph, np.array([0])
    assert len(shard.nearest(far[:1], 21, 32)[0]) == 50


def recall(spark, path):
    e = common.table(spark, path, "embeddings").toPandas()
    got = ann.search(common.table(spark, path, "embeddings")).toPandas()
    x, hits, n = np.stack(e.embedding).astype(float), 0, 0
    ids = e.vec_id.to_numpy()
    for q in ids[ids % 20 == 0]:
        s = x @ x[ids == q][0]
        s[ids == q] = -np.inf
        best = set(ids[np.lexsort((ids, -s))[:20]])
        hits, n = hits + len(best & set(got[got.query_id == q].vec_id)), n + len(best)
    return hits / n


def test_recall_on_the_given_vectors(spark):
    assert recall(spark, "/root/testdata/sf0.1") >= 0.9


def test_classifier_against_direct_normal_equations(spark):
    rng = random.Random(4)
    texts, good = [], []
    for _ in range(220):
        good.append(int(rng.random() < 0.5))
        texts.append(". ".join(" ".join(rng.choice(WORDS) for _ in range(rng.randint(3, 9))).capitalize() for _ in range(rng.randint(1, 5))) if good[-1] else "".join(rng.choice("#$%&AZ 09") for _ in range(rng.randint(5, 90))))
    docs = docs_of(spark, [*texts, texts[3], None, ""], [*range(220), 3, 300, None])
    labels = spark.createDataFrame([(i, g) for i, g in enumerate(good)] + [(5, good[5]), (None, 1), (6, None), (999, 1)], "doc_id long, quality int")
    model = quality.train(clashing(docs), labels, features=24)
    fold = [zlib.crc32(str(i).encode()) % 5 for i in range(220)]
    used = [i for i in range(220) if fold[i]] + [3] * bool(fold[3])  # a repeated document counts twice
    stats = np.array([quality.document_stats(t) for t in texts])
    mean, scale = stats[used].mean(0), stats[used].std(0)
    scale[scale == 0] = 1.0
    assert np.allclose(model.mean, mean) and np.allclose(model.scale[scale > 1e-9], scale[scale > 1e-9])
    fit = [i for i in used if fold[i] > 1]
    x, y = model.lift(stats[fit]), np.array(good)[fit]
    penalty = np.eye(x.shape[1])
    penalty[-1, -1] -= 0.999
    assert np.allclose(model.weights, np.linalg.solve(x.T @ x + penalty, x.T @ y), atol=1e-6)
    got = quality.score_documents(clashing(docs), labels, features=24).collect()
    assert len(got) == 223 and sum(r.doc_id == 3 for r in got) == 2
    assert all(r.score == pytest.approx(model.score(stats[[r.doc_id]])[0]) and r.held_out == (fold[r.doc_id] == 0) and r.predicted == (r.score >= 0.3) for r in got if r.doc_id is not None and r.doc_id < 220)
    kept = [r.doc_id for r in quality.keep_good(clashing(docs), labels, features=24).collect()]
    assert sorted(map(str, kept)) == sorted(str(r.doc_id) for r in got if r.predicted)


def test_split_against_all_splits():
    rng = random.Random(7)
    for _ in range(80):
        counts = {"".join(rng.choice("ab") for _ in range(rng.randint(1, 5))): rng.randint(1, 500) for _ in range(rng.randint(1, 9))}
        model = url_filter.Segmenter.of(counts)
        name = "".join(rng.choice("abc") for _ in range(rng.randint(1, 10)))

        def cost(words):
            return sum(min(model.costs.get(w, math.inf), model.unknown + url_filter.UNKNOWN_LETTER * len(w)) for w in words)

        splits = []
        for cuts in range(1 << (len(name) - 1)):
            at = [0, *(i + 1 for i in range(len(name) - 1) if cuts >> i & 1), len(name)]
            splits.append([name[a:b] for a, b in itertools.pairwise(at)])
        got = model.split(name)
        assert "".join(got) == name and cost(got) == pytest.approx(min(map(cost, splits)))


def test_bayes_by_counts(spark):
    labelled = [("cheap pills", True), ("http://cheap-casino.com/", True), ("city news", False), ("news news", False), ("été", False), (None, True), ("x", None)]
    model, seen = url_filter.train_words(spark.createDataFrame(labelled, "name string, blocked boolean"))
    bad, good = Counter("cheap pills cheap casino".split()), Counter("city news news news été".split())
    assert seen == bad + good
    for w in bad | good:
        assert model.weights[w] == pytest.approx(math.log((bad[w] + 1) / (4 + 6)) - math.log((good[w] + 1) / (5 + 6)))
    pages = spark.createDataFrame([(1, "http://a.com/%C3%A9t%C3%A9", None), (2, "http://été.fr/%zz", "été"), (1, "http://a.com/%C3%A9t%C3%A9", None), (3, "http://cheapcasino.net.org/", "cheap")] + [(None, "http://x.org/fr", None)], "page_id long, url string, html string")
    rows = sorted((str(r.page_id), r.words, r.verdict, r.host, r.path) for r in url_filter.judge_urls(pages, labelled=spark.createDataFrame(labelled, "name string, blocked boolean")).collect())
    assert rows == [("1", "a été", "allow", "a.com", "/%C3%A9t%C3%A9")] * 2 + [("2", "été fr zz", "allow", "été.fr", "/%zz"), ("3", "cheap casino", "block", "cheapcasino.net.org", "/"), ("None", "x fr", "allow", "x.org", "/fr")]


def brute_hits(doc, item, budget):
    """Ends in the normalised text where an occurrence within budget stops, by the full table."""
    row = [0] * (len(doc) + 1)
    for i, a in enumerate(item, 1):
        new = [i]
        for j, b in enumerate(doc, 1):
            new.append(min(row[j - 1] + (a != b), row[j] + 1, new[-1] + 1))
        row = new
    return {j for j, d in enumerate(row) if d <= budget}


def test_occurrences_against_the_full_table(spark):
    rng = random.Random(21)
    letters = "abcd "
    items = ["".join(rng.choice(letters) for _ in range(rng.randint(18, 70))) for _ in range(8)]
    items = [t for t in map(decontaminate.normalised, items) if len(t) >= 16]

    def edited(t):
        t = list(t)
        for _ in range(rng.randint(0, 7)):
            k = rng.randrange(len(t))
            t[k : k + rng.randint(0, 1)] = [rng.choice(letters)] * rng.randint(0, 1)
        return "".join(t)

    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 60))) + edited(rng.choice(items)) + "".join(rng.choice(letters) for _ in range(rng.randint(0, 200))) for _ in range(60)] + [None, "", items[0], items[0].upper()]
    docs = docs_of(spark, texts + [items[0]], [*range(len(texts)), 62])
    bench = spark.createDataFrame(list(enumerate(items)) + [(0, items[0])], "item_id long, text string")
    got = decontaminate.contaminated(clashing(docs), bench).collect()
    want = {(d, i) for d, t in enumerate(texts) for i, item in enumerate(items) if brute_hits(decontaminate.normalised(t), item, len(item) // decontaminate.CHARS_PER_EDIT)}
    assert {(r.doc_id, r.item_id) for r in got} == want and len(want) > 30
    for r in got:
        t, item = decontaminate.normalised(texts[r.doc_id]), items[r.item_id]
        assert r.distance <= len(item) // decontaminate.CHARS_PER_EDIT and brute_distance(item, t[r.hit_start : r.hit_end]) <= r.distance
    assert sum(r.doc_id == 62 and r.item_id == 0 for r in got) == 2
    small = decontaminate.contaminated(docs, bench, block_chars=100).collect()
    assert sorted(map(tuple, small)) == sorted(map(tuple, got))
    assert sorted(r.doc_id for r in decontaminate.drop_contaminated(docs, bench).collect()) == sorted(set(range(len(texts))) - {d for d, _ in want})


def test_pipeline_by_plain_code(spark, small):
    import corpus_pipeline

    docs, labels, bench = (common.table(spark, small, t) for t in ("documents", "labels", "benchmark"))
    good = {r.doc_id for r in quality.score_documents(docs, labels).collect() if r.predicted}
    rows = sorted((r.doc_id, r.text, r.source) for r in docs.collect() if r.doc_id in good)
    first = [c for _, c in brute_components([t for _, t, _ in rows])]
    rows = [r for k, r in enumerate(rows) if first[k] == k]
    items = [decontaminate.normalised(r.text) for r in bench.collect()]
    items = [t for t in items if t]

    def held(text):
        for item in items:
            budget = len(item) // decontaminate.CHARS_PER_EDIT if len(item) >= decontaminate.MIN_ITEM_CHARS else 0
            # a piece that an occurrence leaves alone is a necessary condition, cheap to test
            if any(p in text for p, _ in decontaminate.pieces_of(item, budget)) and (decontaminate.bounded_distance(item, text, budget) if len(item) >= decontaminate.MIN_ITEM_CHARS else re.search(rf"(?<!\w){re.escape(item)}(?!\w)", text)):
                return True
        return False

    rows = [r for r in rows if not held(decontaminate.normalised(r[1]))]
    clean = []
    for i, text, source in rows:
        spans = [(m.start(), m.end()) for n, p, g, least in PATTERNS for m in re.finditer(p, text or "") if len(m[g]) >= least]
        for rule in secrets.RULES[3:]:
            spans += [m.span() for m in re.finditer(rule.pattern, text or "")]
        clean.append((i, brute_redaction(text or "", spans), source))
    want = mixing.mix(docs_of(spark, [t for _, t, _ in clean], [i for i, _, _ in clean], [s for _, _, s in clean]))
    got = {r.doc_id: r for r in corpus_pipeline.run(spark, small).collect()}
    assert {i: len(re.findall(r"[^\x20\x09-\x0D]+", t)) for i, t, _ in clean} == {i: r["size"] for i, r in got.items()} and len(got) < len(good)
    assert {r.doc_id: (r.source_size, r.target, r.taken) for r in want.collect()} == {i: (r.source_size, r.target, r.taken) for i, r in got.items()}


def test_repeated_and_awkward_rows(spark):
    text = "Released under the MIT License. " + "token=abcdef12 " + "w " * 60_000
    docs = clashing(docs_of(spark, [text, text, None, "", " \t"], [1, 1, None, 2, 2]))
    found = [tuple(r) for r in licenses.scan_licenses(docs).collect()]
    assert len(found) == 5 and found.count((1, "MIT", "MIT", 1.0, 2)) == 2
    assert sum(r.doc_id == 1 and r.n_assign == 1 for r in secrets.find_secrets(docs).collect()) == 2
    scores = quality.score_documents(docs, spark.createDataFrame([(1, 1), (2, 0)], "doc_id long, quality int")).collect()
    assert len(scores) == 5 and len({r.score for r in scores if r.doc_id == 1}) == 1
    assert len(mixing.mix(docs).collect()) == 5
    tie = (("B", "notice", "alpha beta gamma delta"), ("A", "notice", "alpha beta gamma delta"))
    assert tuple(licenses.scan_licenses(docs_of(spark, ["x alpha beta gamma delta y"]), tie).first()) == (0, "A,B", "A", 1.0, 2)


def test_whole_licence_texts(spark):
    code = " ".join(random.Random(1).choices(WORDS, k=300))
    three = f"{licenses._BSD_TERMS}\n{licenses._BSD_NAMES}\n\n{licenses._BSD_AS_IS}"
    texts = [f"/* Copyright someone\n{three} */ {code}", f"{code} {licenses._BSD_TERMS} {licenses._BSD_AS_IS}", f"{code} {licenses._BSD_TERMS.replace('forms', 'shapes')}", code]
    got = {r.doc_id: r for r in licenses.scan_licenses(docs_of(spark, texts)).collect()}
    assert [got[i].best_license for i in range(4)] == ["BSD-3-Clause", "BSD-2-Clause", None, None] and got[0].best_dice == got[1].best_dice == 1.0


@pytest.mark.parametrize("block", (2, 512))
def test_links_within_a_hub_against_brute_force(spark, block):
    rng = random.Random(block)
    base = [rng.getrandbits(63) for _ in range(400)]
    sets = {}
    for k in range(70):
        n = rng.choice((3, 4, 30, 40, 53, 54, 71, 95, 96, 200))
        own = set(rng.sample(base[: rng.choice((n, n + 5, 400))], n))
        sets[k] = np.array(sorted(own | {rng.getrandbits(63) for _ in range(rng.randint(0, 3))}), dtype=np.uint64)
    label = {k: rng.randrange(40) for k in sets}
    hub = {k: rng.randrange(2) for k in sets}
    nodes = spark.createDataFrame([(k, label[k], hub[k], len(s)) for k, s in sets.items()], "node long, label long, hub long, n long")
    table = spark.createDataFrame([(k, bytearray(s.tobytes())) for k, s in sets.items()], "node long, toks binary")
    got = {(r.a, r.b) for r in ngram_join._links_of_hubs(nodes, table, 75, block).collect()}
    linked = lambda a, b: 100 * len(np.intersect1d(sets[a], sets[b])) >= 75 * len(np.union1d(sets[a], sets[b]))
    assert all(linked(a, b) and hub[a] == hub[b] and label[a] != label[b] for a, b in got)
    for a, b in itertools.permutations(sets, 2):
        if hub[a] == hub[b] and label[a] != label[b] and linked(a, b):
            # of each node a link to every label is told, from one side at least
            assert any((x == a and label[y] == label[b]) or (y == a and label[x] == label[b]) or (x == b and label[y] == label[a]) or (y == b and label[x] == label[a]) for x, y in got)
