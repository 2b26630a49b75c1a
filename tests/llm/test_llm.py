"""The text operators against brute force on small fixtures, with nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns."""

import base64
import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest

from roundjoin.llm import ann, common, decontaminate, html_text, licenses, mixing, ngram_join, quality, secrets, url_filter, warc

DOC = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = [f"w{i}" for i in range(400)]


def docs_of(spark, texts, ids=None, sources=None):
    ids = ids if ids is not None else range(len(texts))
    sources = sources or ["s"] * len(texts)
    return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t)) for i, t, s in zip(ids, texts, sources, strict=True)], DOC)


def clashing(df):
    """The table with columns that differ from others in case only, or are named like results."""
    return df.toDF(*df.columns).selectExpr("*", "1 AS score", "'x' AS TEXT", "2 AS node", "3 AS size", "4 AS html_", "5 AS `Doc_Id`")


def texts_near(seed=1, n=60):
    rng = random.Random(seed)
    base = [" ".join(rng.choice(WORDS) for _ in range(rng.randint(5, 120))) for _ in range(n // 4)]
    out = list(base)
    while len(out) < n:
        w = rng.choice(base).split()
        for _ in range(rng.randint(0, 5)):
            w[rng.randrange(len(w))] = rng.choice(WORDS)
        out.append(" ".join(w))
    return [*out, "", None, "one two", "One TWO", "a b c d e", " \t\n", "z " * 3000]


def brute_components(texts):
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
        sets.append(frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset())
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and 100 * len(a & b) >= 75 * len(a | b):
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    return [(len(s), find(i)) for i, s in enumerate(sets)]


def test_jaccard_components(spark):
    texts = texts_near()
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.jaccard_components(clashing(docs_of(spark, texts)), frequent=4).collect()}
    assert got == dict(enumerate(brute_components(texts)))


def test_jaccard_stage_keeps_one_of_each(spark):
    texts = [*texts_near(2, 24), "a b c d e"]
    ids = [*range(len(texts) - 1), texts.index("a b c d e")]
    kept = Counter(r.doc_id for r in ngram_join.keep_one_of_each_group(docs_of(spark, texts, ids)).collect())
    want = brute_components(texts[:-1])
    assert kept == Counter(i for i, (n, c) in enumerate(want) if n == 0 or c == i)


def test_empty_tables(spark):
    none = docs_of(spark, [])
    labels = spark.createDataFrame([], "doc_id long, quality int")
    assert ngram_join.jaccard_components(none).count() == 0
    assert quality.score_documents(none, labels).count() == 0
    assert licenses.scan_licenses(none).count() == 0 and secrets.find_secrets(none).count() == 0 and mixing.mix(none).count() == 0
    assert decontaminate.contaminated(none, spark.createDataFrame([], "item_id long, text string")).count() == 0
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    assert url_filter.judge_urls(pages).count() == 0 and html_text.extract_main_text(pages).count() == 0 and warc.round_trip(pages).count() == 0
    assert ann.search(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_quality(spark, small):
    docs, labels = common.table(spark, small, "documents"), common.table(spark, small, "labels")
    got = quality.score_documents(docs.unionByName(docs_of(spark, [None, "", "x" * 100_000], [10**6, 10**6 + 1, None])), labels).toPandas()
    assert len(got) == docs.count() + 3 and got.score.between(0, 1).all()
    both = got.merge(labels.toPandas(), on="doc_id")
    held = both[both.held_out]
    assert (held.predicted == held.quality).mean() >= 0.9
    x, y = quality.isotonic(np.array([1.0, 2, 3, 4]), np.array([0, 1, 0, 1.0]), np.ones(4))
    assert y.tolist() == [0, 0.5, 1] and x.tolist() == [1, 2.5, 4]
    assert set(r.score for r in quality.score_documents(docs.limit(3), labels.limit(0)).collect()) == {0.5}


def brute_distance(p, t):
    row = [0] * (len(t) + 1)
    for i, a in enumerate(p, 1):
        new = [i]
        for j, b in enumerate(t, 1):
            new.append(min(row[j - 1] + (a != b), row[j] + 1, new[-1] + 1))
        row = new
    return min(row)


def test_myers_and_decontamination(spark):
    rng = random.Random(4)
    for _ in range(200):
        p, t = ("".join(rng.choice("abc") for _ in range(rng.randint(1, 80))) for _ in range(2))
        got, want = decontaminate.bounded_distance(p, t, len(p)), brute_distance(p, t)
        assert (got[0] if got else len(p)) == want or want == len(p)
    item = "The quick brown fox jumps over the lazy dog while seventeen zebras watch"
    near = item.replace("brown", "brwn").replace("zebras", "zebra")
    texts = ["x " * 50 + item.upper() + " y" * 50, "a " + near, "nothing of it", None, "", item[:40], "q" * 50_000 + item]
    bench = spark.createDataFrame([(1, item), (2, None), (3, ""), (1, item)], "item_id long, text string")
    hits = {(r.doc_id, r.item_id): r.distance for r in decontaminate.contaminated(clashing(docs_of(spark, texts)), bench).collect()}
    assert hits == {(0, 1): 0, (1, 1): 2, (6, 1): 0}
    assert sorted(r.doc_id for r in decontaminate.drop_contaminated(docs_of(spark, texts), bench).collect()) == [2, 3, 4, 5]


def test_short_items_are_found_exactly(spark):
    bench = spark.createDataFrame([(1, "What is 7 x 8?"), (2, "光合作用的产物是什么？"), (3, "an area"), (4, " \n")], "item_id long, text string")
    texts = ["so what is  7 x 8? Say", "what is 7 x 9?", "请问光合作用的产物是什么？谢谢", "in an area.", "an areas, Japan area", "Span area", None, ""]
    docs = docs_of(spark, texts)
    assert {(r.doc_id, r.item_id, r.distance) for r in decontaminate.contaminated(docs, bench).collect()} == {(0, 1, 0), (2, 2, 0), (3, 3, 0)}
    assert sorted(r.doc_id for r in decontaminate.drop_contaminated(docs, bench).collect()) == [1, 4, 5, 6, 7]


PATTERNS = (("assign", r"(?ai:(password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 2, 6), ("access", r"AKIA[A-Z0-9]+", 0, 20), ("hex", r"[0-9a-f]+", 0, 24))
SECRET_TEXTS = ["token = \"24be64439e3e49cf46b2d7c90f3602a3\" é", "secret=token:abcdefg PassWord='hunter22'", "ñ AKIA" + "B" * 16 + " AKIA1", None, "", "clean", "api_key: abc12345," * 400, "f" * 23 + " " + "f" * 24]


def test_secrets(spark):
    got = {r.doc_id: r for r in secrets.find_secrets(clashing(docs_of(spark, SECRET_TEXTS))).collect()}
    for i, t in enumerate(SECRET_TEXTS):
        spans = sorted((m.start(), k, n, m.end()) for k, (n, p, g, least) in enumerate(PATTERNS) for m in re.finditer(p, t or "") if len(m[g]) >= least)
        said = ",".join(f"{n}:{a}:{b}" for a, _, n, b in spans)
        assert got[i].base_sha256 == hashlib.sha256(said.encode()).hexdigest() and got[i].n_assign == sum(s[2] == "assign" for s in spans)
    first = secrets.update_ledger(docs_of(spark, SECRET_TEXTS[:4])).cache()
    later = secrets.update_ledger(docs_of(spark, SECRET_TEXTS), first)
    assert later.select("blob").distinct().count() == 8 - 5  # the empty text is the blob of the null one
    assert sorted(map(tuple, secrets.find_secrets(docs_of(spark, SECRET_TEXTS), first).collect())) == sorted(map(tuple, got.values()))
    clean = {r.doc_id: r for r in secrets.redact_secrets(docs_of(spark, SECRET_TEXTS)).collect()}
    assert clean[0].text == "[SECRET]\" é" and clean[0].n_chars == len(clean[0].text) and clean[5].text == "clean" and clean[3].text is None and len(clean) == 8


def test_private_key_goes_whole(spark):
    key = "-----BEGIN RSA PRIVATE KEY-----\nProc-Type: 4,ENCRYPTED\n\n" + "MIIEow+/=\n" * 2000 + "-----END RSA PRIVATE KEY-----"
    texts = ["before " + key + " after", "-----BEGIN PRIVATE KEY----- and prose that goes on", key + "\n" + key]
    got = {r.doc_id: r.text for r in secrets.redact_secrets(docs_of(spark, texts)).collect()}
    assert got == {0: "before [SECRET] after", 1: "[SECRET] and prose that goes on", 2: "[SECRET]\n[SECRET]"}


def test_mixing(spark):
    rng = random.Random(3)
    texts = [" ".join("x" * rng.randint(1, 60)) for _ in range(400)] + [None, ""]
    sources = [rng.choice(("a", "b", "c", None)) if i % 3 else "a" for i in range(402)]
    got = mixing.mix(clashing(docs_of(spark, texts, sources=sources)), bucket_rows=20).toPandas()
    want = mixing.mix(docs_of(spark, texts, sources=sources), bucket_rows=20).toPandas()
    assert got.sort_values("doc_id").values.tolist() == want.sort_values("doc_id").values.tolist()
    assert (got.taken <= 2 * got["size"]).all()
    got["source"] = [sources[i] or "~" for i in got.doc_id]
    by = got.groupby("source").agg(t=("target", "first"), n=("taken", "sum"), s=("size", "sum"))
    assert ((by.n - by.t).abs() <= 60).all() and abs(by.t.sum() - 1.5 * by.s.sum()) < 1e-6
    assert mixing.share_out([10, 100, 100], [3, 1, 2], 200, 2) == pytest.approx([20, 60, 120])
    assert mixing.emit(mixing.plan_copies(docs_of(spark, texts, sources=sources))).count() > 0


def test_urls(spark):
    urls = ["http://a.example.net/en/1", "https://x.net/q?u=http://y", "HTTP://Example.COM/de/", "http://b.org/fr/z", "http://notexample.com/en/1", "http://cheap-pills.example.com/en/1", "http://citynews.example.com/", None, "no scheme", "http://h#frag"]
    pages = spark.createDataFrame([(i, u, "cheap pills city news pills news" if i % 2 else None) for i, u in enumerate(urls)], "page_id long, url string, html string")
    got = {r.page_id: r for r in url_filter.judge_urls(pages.selectExpr("*", "1 AS host", "2 AS verdict")).collect()}
    assert [(got[i].rule, got[i].verdict) for i in range(5)] == [("example.net/en/", "allow"), ("net/", "block"), ("example.com/de/", "block"), ("org/fr/", "allow"), (None, "allow")]
    assert got[5].verdict == "block" and got[6].words.startswith("city news") and got[6].verdict == "allow"
    assert [(got[i].host, got[i].path) for i in (2, 7, 8, 9)] == [("example.com", "/de/"), ("", ""), ("", ""), ("h", "")]


def test_long_names_are_split(spark):
    pages = spark.createDataFrame([(1, "http://" + "cheappills" * 500 + ".com/", "cheap pills"), (2, "http://h/" + "q" * 50_000, None)], "page_id long, url string, html string")
    got = {r.page_id: r for r in url_filter.judge_urls(pages).collect()}
    assert got[1].words == " ".join(["cheap pills"] * 500) and got[1].verdict == "block" and got[2].verdict == "allow"


def test_all_corpus_words_are_known(spark):
    common_words = " ".join("".join(chr(97 + k // 26**i % 26) for i in range(4)) + "q" for k in range(20_500))
    urls = ["http://a.example.com/xenophobe", "http://casinova.example.com/", "http://pillsbury.example.com/", "http://unheard.example.com/casinova"]
    pages = spark.createDataFrame([(i, u, (common_words + " ") * 8 if i == 0 else "xenophobe casinova pillsbury " * 2) for i, u in enumerate(urls)], "page_id long, url string, html string")
    got = {r.page_id: r for r in url_filter.judge_urls(pages, rules={}).collect()}
    assert got[0].words.endswith("xenophobe") and [(got[i].words, got[i].verdict) for i in (1, 2)] == [("casinova", "allow"), ("pillsbury", "allow")]
    html = [r.html for r in pages.collect()]
    counts = Counter(w for h in html for w in re.findall("[a-z]{2,20}", h))
    known = Counter(w for x in (*url_filter.BLOCKED_NAMES, *url_filter.ALLOWED_NAMES) for w in x.split())
    model = url_filter.Segmenter.of(counts + known)
    for i, names in enumerate((["a", "xenophobe"], ["casinova"], ["pillsbury"], ["unheard", "casinova"])):
        assert got[i].words == " ".join(w for x in names for w in model.split(x))


def test_warc(spark):
    html = ["<p>é</p>", "same", "same", None, "", "a\r\n\r\nWARC/1.1\r\nb", "same", "x" * 200_000]
    pages = spark.createDataFrame([(10 - i, f"http://h/{i}\n", h) for i, h in enumerate(html)] + [(10**12, None, "y")], "page_id long, url string, html string")
    got = {r.page_id: r for r in warc.round_trip(pages.selectExpr("*", "1 AS size", "2 AS digest")).collect()}
    first = {}
    for i, h in sorted([(10 - i, h) for i, h in enumerate(html)] + [(10**12, "y")]):
        body = (h or "").encode()
        digest = base64.b32encode(hashlib.sha1(body).digest()).decode()
        own = first.setdefault(digest, i)
        assert (got[i].payload_bytes, got[i].payload_digest, got[i].record_type, got[i].refers_to) == (len(body), digest, "response" if own == i else "revisit", None if own == i else own) and got[i].intact


def test_ann_recall(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(600, 16))
    x[100:110] = x[100]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(700, None), (720, [0.0] * 16), (740, [float("nan")] * 16), (760, [None] * 16)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").selectExpr("*", "1 AS rank", "2 AS shard")
    got = ann.search(df, shard_rows=200).toPandas()
    hits = 0
    for q in range(0, 600, 20):
        s = x @ x[q]
        s[q] = -np.inf
        best = np.lexsort((np.arange(600), -s))[:20]
        own = got[got.query_id == q].sort_values("rank")
        assert own["rank"].tolist() == list(range(1, 21)) and np.allclose(own.score, x[own.vec_id] @ x[q])
        hits += len(set(best) & set(own.vec_id))
    assert hits / 600 >= 0.9 and got.query_id.nunique() == 30


def test_html(spark):
    assert np.mean([html_text.default_model().decode(r) == y for r, y in (html_text.labelled_blocks(*p) for p in html_text.labelled_pages(60, 77))]) > 0.95
    page = "<html><head><title>t</title><script>var a='</p>'</script></head><body><nav><a href=/>Menu</a></nav><article><h1>Head &amp; line</h1><p>One  two<p>three <b>four</b>five.</article><div class=comments><p>First!</p></div><footer>&copy; me</footer>"
    pages = spark.createDataFrame([(1, "u", page), (2, None, None), (3, "v", ""), (4, "w", "<article><p>" + "word " * 30_000)], "page_id long, url string, html string").selectExpr("*", "1 AS text", "2 AS n_chars")
    got = {r.page_id: r for r in html_text.extract_main_text(pages).collect()}
    assert got[1].text == "Head & line One two three fourfive." and got[1].n_chars == len(got[1].text)
    assert (got[2].text, got[3].text) == ("", "") and got[4].n_chars == 30_000 * 5 - 1


def test_licenses(spark):
    texts = ["x\nReleased under the MIT License.\ny", "Licensed under the Apache License Version 2.0", licenses._MIT_TERMS + "\n\n" + licenses._AS_IS, "no licence", None, "", "software " * 20_000]
    got = {r.doc_id: r for r in licenses.scan_licenses(clashing(docs_of(spark, texts))).collect()}
    assert [got[i].licenses for i in range(7)] == ["MIT", "Apache-2.0", "MIT", "", "", "", ""] and got[0].best_dice == 1.0 and got[3].best_dice is None
    bag = licenses.template_bigrams("a b c d")
    assert sum(bag.values()) == 3 and licenses.size_range(3, 0.8) == (2, 4)


def test_html_without_end_tags():
    texts = lambda page: [x.text for x in html_text.leaf_blocks(page)]
    for head in ("<head><title>x</title><body>", "<head><meta charset=utf-8><style>p{}</style>", "<head><body>", "<head>\n</head><body>"):
        assert texts(f"<html>{head}<article><p>text") == ["text"]
    assert texts("<head><title>x</title>bare text<p>more") == ["bare text", "more"]
    for cut_off in ("<button>Go", "<select><option>a<option>b", "<object data=x>", "<button>Go<button>On", "<svg><path d=x>"):
        assert texts(f"<article><p>one</p>{cut_off}<p>two</p><div>three</div></article><p>four") == ["one", "two", "three", "four"], cut_off
        assert texts(f"<article><p>one {cut_off}</article><p>four") == ["one", "four"], cut_off
    assert texts("<p>one<select><option>a<option>b</select> three") == ["one three"]
    assert texts("<button><div>Go</div> on</button><p>two") == ["two"]
    assert texts("<article><p>so <math><mi>x</mi><mo>=</mo><mn>1</mn></math> holds</article>") == ["so x=1 holds"]


def best_stretch(text, template):
    """Dice coefficient of the best run of words, by brute force."""
    words, bag = re.findall(r"[^\W_]+", text.lower()), licenses.template_bigrams(template)
    pairs, size = list(zip(words, words[1:], strict=False)), sum(bag.values())
    best = 0.0
    for i in range(len(pairs)):
        run = Counter()
        for j in range(i, min(len(pairs), i + 2 * size)):
            run[pairs[j]] += 1
            best = max(best, 2 * sum((run & bag).values()) / (j - i + 1 + size))
    return best


def test_licenses_inside_longer_texts(spark):
    rng = random.Random(6)
    gpl = next(t for n, f, t in licenses.TEMPLATES if (n, f) == ("GPL-3.0", "header"))
    one, two = gpl.split("This program is distributed")
    header = f"# Copyright someone\n#\n# {one}\n#\n# This program is distributed{two}\n#\n"
    code = "\n".join(" ".join(rng.choices(WORDS, k=12)) for _ in range(200))
    texts = [code + "\n\n" + header + "\n" + code, code.replace("\n", " ") + " see the notes. Released under the MIT License. " + code.replace("\n", " ")]
    texts += [code + "\n\n" + licenses._MIT_TERMS.replace("to deal", "\n\nto deal") + "\n\n" + licenses._AS_IS + "\n\n" + code, "Released under the MIT License. " * 3 + code]
    got = [tuple(r)[1:] for r in licenses.scan_licenses(docs_of(spark, texts)).orderBy("doc_id").collect()]
    assert got == [("GPL-3.0", "GPL-3.0", 1.0, 1), ("MIT", "MIT", 1.0, 2), ("MIT", "MIT", 1.0, 2), ("MIT", "MIT", 1.0, 6)]  # "under the MIT License" matches both notices
    words = [*re.findall(r"\w+", gpl.lower()), "x", "y"]
    made = []
    for _ in range(40):
        w = gpl.split() * rng.randint(1, 2)
        for _ in range(rng.randint(5, 24)):
            w[rng.randrange(len(w))] = rng.choice(words)
        made.append(" ".join(rng.choices(words, k=rng.randint(0, 40))) + " " + rng.choice((" ", "\n\n")).join(w) + " and so on")
    for r in licenses.scan_licenses(docs_of(spark, made), (("GPL-3.0", "header", gpl),)).collect():
        want = best_stretch(made[r.doc_id], gpl)
        assert r.best_dice == (pytest.approx(want) if want >= 0.8 else None)


def test_pipeline(spark, small):
    import corpus_pipeline

    docs = common.table(spark, small, "documents")
    texts = {r.doc_id: r.text for r in docs.collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before, docs = docs, common.cut(stage(spark, docs, small))
        assert docs.columns == list(common.DOC_COLUMNS), name
        ids = {r.doc_id for r in docs.collect()}
        if name == "n-gram Jaccard join":
            order = sorted(r.doc_id for r in before.collect())
            want = brute_components([texts[i] for i in order])
            assert ids == {order[c] for _, c in want}
    assert corpus_pipeline.run(spark, small).count() == docs.count()


def test_components(spark):
    rng = random.Random(8)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)]
    got = {r.node: r.label for r in common.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    least = {x: x for e in edges for x in e if e[0] != e[1]}
    for _ in range(200):
        for a, b in edges:
            if a != b:
                least[a] = least[b] = min(least[a], least[b])
    assert got == least
