import hashlib
import math
import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

from knnscope.io import table
from knnscope.llm import htmltext, langid, pii, quality, toxicity, urlfilter
from tests.llm.conftest import ODD_TEXTS

SF = "/root/testdata/sf0.01"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def quality_counts(text):
    w = WORD.findall(text or "")
    seen = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {j for i in range(len(w) - 4) if seen[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered)


def test_quality_counts_equal_brute_force(make_docs):
    texts = [*ODD_TEXTS, "a b c d e a b c d e", "x\ny\nx\n \nx", "a b c d e f", "aa " * 300, "\x0bv\x0cw\rx #|&$ <t>", "p q r s t u p q r s t v " * 40, "abc \u0085", "abc \u2028", " a \u0085 "]
    got = {r.doc_id: r for r in quality.judge(make_docs(texts)).collect()}
    for i, t in enumerate(texts):
        r = got[i]
        want = quality_counts(t)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, t
        assert r.base_failed == (want[0] < 10 or 100 * want[4] > 20 * want[0])
        assert not (r.kept and r.base_failed)
    assert quality.judge(make_docs([])).count() == 0


def test_quality_keeps_clean_and_drops_junk(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    rows = quality.judge(docs).filter("NOT base_failed").join(labels, "doc_id").groupBy("quality").agg(F.avg(F.col("kept").cast("int")).alias("k")).collect()
    kept = {r.quality: r.k for r in rows}
    assert kept[1] > 0.99 and kept.get(0, 0) < 0.1
    assert set(quality.passing(docs).columns) == set(docs.columns)


def test_quality_fences_follow_the_group(make_docs):
    def text(i, symbols):
        return " ".join(f"w{i}x{j}" for j in range(100)) + " " + " ".join(["#"] * symbols)

    plain = make_docs([text(i, 0) for i in range(250)] + [text(250, 20)], source="prose")
    marked = make_docs([text(i, 15 + i % 10) for i in range(250)] + [text(250, 20)], first=1000, source="code")
    got = {r.doc_id: r for r in quality.judge(plain.unionByName(marked)).collect()}
    assert not got[250].base_failed and got[250].failed == ["symbol_ratio"] and got[1250].kept
    assert all(r.kept for k, r in got.items() if k != 250)


def base(text):
    patterns = {
        "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
        "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    }
    found = []
    for n, (kind, p) in enumerate(patterns.items()):
        for m in re.finditer(p, text):
            digits = re.sub("[^0-9]", "", m[0])
            luhn = sum(int(c) if i % 2 == 0 else int(c) * 2 - 9 * (int(c) > 4) for i, c in enumerate(reversed(digits))) % 10 == 0
            ok = {
                "email": True, "ip": all(int(x) <= 255 for x in m[0].split(".") if kind == "ip"), "card": 14 <= len(digits) <= 19 and luhn,
                "phone": 10 <= len(digits) <= 15,
            }[kind]
            if ok:
                found.append((m.start(), n, f"{kind}:{m.start()}:{m.end()}"))
    return ",".join(x[2] for x in sorted(found))


PII = [
    *ODD_TEXTS, "a@b.cc_d@e.ff 1.2.3.4.5.6.7.8 300.1.1.1 007.1.1.1 4387513035237269, +1 (988) 555-2485 x", "é\U0001f600 x@y.z, 4387 5130 3523 7269",
    "a@b a@b.c@d.e.f +1234567890 +12 12345678901234567890123", "x" * 5000 + "@y.zz", "1.2.3 9.9.9.9999 0.0.0.0 ++4915112345678-",
]


def test_base_spans_equal_brute_force(make_docs):
    got = {r.doc_id: r for r in pii.report(make_docs(PII)).collect()}
    for i, t in enumerate(PII):
        assert got[i].spans == base(t or ""), t
    assert pii.report(make_docs([])).count() == 0


def test_disclosing_terms_are_found_and_sanitised(make_docs):
    near = [f"today number{k} Zebedeus Quill wrote from zq@mail.org about item{k} and" for k in range(6)]
    other = [f"then row{k} someone wrote from user{k}@host{k}.org about thing{k} and" for k in range(150)]
    docs = make_docs([*near, *other, "Zebedeus is elsewhere", None])
    rows = {r.doc_id: r.spans for r in pii.report(docs).collect()}
    assert all("term:" in rows[i] for i in range(6)) and not any("term:" in rows[i] for i in range(6, 158))
    clean = {r.doc_id: r.text for r in pii.sanitise(docs).collect()}
    assert "zq@mail" not in clean[0] and "Zebedeus" not in clean[0] and "<EMAIL>" in clean[0]
    assert clean[156] == "Zebedeus is elsewhere" and clean[157] is None
    assert pii.sanitise(docs).columns == docs.columns


def test_a_name_beside_its_only_address_is_removed_everywhere(make_docs):
    far = " and then the rest of it goes on and on" * 4
    docs = make_docs([f"By Zebedeus Quill, zebedeus.quill@mail.org wrote the{far} so QUILL left Quillon. the.1@x.org", *(f"the row{k} is here" for k in range(150))])
    spans = {r.doc_id: r for r in pii.report(docs).collect()}
    assert spans[0].n_term == 3 and sum(r.n_term for r in spans.values()) == 3
    text = next(r.text for r in pii.sanitise(docs).collect() if r.doc_id == 0)
    assert "Quillon" in text and not re.search(r"\b(zebedeus|quill)\b", text.lower()) and "wrote the and" in text


def test_a_secret_reveals_itself_and_goes(make_docs):
    docs = make_docs(['the token = "04dbebab91ab85687d33eeaaf9ac699e1188f962" and so on', *(f"the row{k} and averyveryverylongword here" for k in range(60)), "x" * 40 + " " + "7" * 40])
    spans = {r.doc_id: r for r in pii.report(docs).collect()}
    assert spans[0].spans == "term:13:53" and sum(r.n_term for r in spans.values()) == 1
    assert {r.text for r in pii.sanitise(docs).filter("doc_id = 0").collect()} == {'the token = "" and so on'}


def test_copies_do_not_hide_a_disclosing_term(make_docs):
    near = [f"today number{k} Zebedeus wrote from zq@mail.org about item{k} and" for k in range(4)]
    other = [f"then row{k} someone wrote from user{k}@host{k}.org about thing{k} and" for k in range(150)]
    rows = {r.doc_id: r.spans for r in pii.report(make_docs([*near, *other, *near[:1] * 50])).collect()}
    assert all("term:14:22" in rows[i] for i in (*range(4), 154, 203)) and "term:" not in rows[4]


def test_terms_are_counted_exactly(make_docs):
    docs = make_docs(["one two Two", "two x-y", "two x-y", None, ""])
    got = {r.term: r.n for r in pii.term_counts(pii.distinct_texts(docs)).collect()}
    assert {k: v for k, v in got.items() if k} == {"one": 1, "two": 2, "x-y": 1}


def test_language_on_held_out_rows(spark, make_docs):
    docs = table(spark, SF, "documents")
    model = langid.fit(docs, langid.not_held_out(), per_language=120)
    held = docs.filter(~langid.not_held_out())
    rows = langid.predict(held, model).join(held, "doc_id").collect()
    assert sum(r.lang_pred == r.lang for r in rows) / len(rows) > 0.95
    assert sum(r.rejected for r in rows) / len(rows) < 0.01
    odd = {r.doc_id: r for r in langid.predict(make_docs([*ODD_TEXTS, "12 34 !!"]), model).collect()}
    assert all(odd[i].lang_pred == "und" and odd[i].score == 0 and odd[i].rejected for i in (0, 1, 2, len(ODD_TEXTS)))
    assert langid.predict(make_docs(["hello"]), langid.fit(docs.limit(0))).first().lang_pred == "und"
    assert langid.accepted(docs, model).columns == docs.columns


def test_toxicity(spark, make_docs):
    docs, labels = table(spark, "/root/testdata/sf0.1", "documents"), table(spark, "/root/testdata/sf0.1", "labels")
    model = toxicity.fit(toxicity.labelled_rows(docs, labels))
    held = toxicity.score_table(docs, model).join(labels, "doc_id").filter(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0)
    rows = held.collect()
    assert sum(r.predicted == r.toxic for r in rows) / len(rows) > 0.975
    odd = toxicity.score_table(make_docs(ODD_TEXTS), model).collect()
    assert len(odd) == len(ODD_TEXTS) and all(0 <= r.score <= 1 for r in odd) and not odd[0].predicted
    assert toxicity.score_table(make_docs([]), model).count() == 0
    none = toxicity.fit(toxicity.labelled_rows(docs, labels.filter("toxic = 0")))
    assert toxicity.score_table(make_docs(["anything"]), none).first().score < 0.01


def toxic_rows(spark):
    texts = [(f"you {a} fool {b} and {c}", 1) for a in ("old", "mad", "sad", "bad") for b in ("there", "here") for c in "xyz"]
    texts += [(f"the {a} house {b} and {c}", 0) for a in ("old", "mad", "sad", "big", "red") for b in ("there", "here", "now") for c in "xyz"]
    return spark.createDataFrame([(i, t, y) for i, (t, y) in enumerate(texts)] + [(900, None, 0), (901, "", 1), (900, "the end", 0)], "doc_id long, text string, toxic int")


def test_kneser_ney_estimates_equal_brute_force(spark):
    rows = toxic_rows(spark)
    pairs = [set(), set()]
    for r in rows.collect():
        w = [x.strip(toxicity.OUTER) for x in (r.text or "").lower().split()]
        pairs[r.toxic].update(zip(w, [None, *w]))
    n = [Counter(w for w, _ in p) for p in pairs]
    words = set(n[0]) | set(n[1])
    q = [{w: max(c[w] - 2, 0) for w in words} for c in n]
    shared = {w: (n[0][w] + n[1][w] + 0.5) / (sum(n[0].values()) + sum(n[1].values()) + 0.5 * len(words)) for w in words}
    p = [{w: 0.95 * q[c][w] / sum(q[c].values()) + 0.05 * shared[w] for w in words} for c in (0, 1)]
    want = {w: math.log(0.98 + 0.02 * p[1][w] / p[0][w]) for w in words}
    got = {r.expression: r.diff for r in toxicity.differences(toxicity.context_counts(rows, flush_at=5)).collect()}
    assert got["fool"] > 0 > got["house"] and "here" in want
    for w in words:
        assert got.get(w, 0.0) == pytest.approx(want[w], abs=1e-12)


def test_a_table_too_large_to_ship_gives_the_same_scores(spark, make_docs, monkeypatch):
    rows = toxic_rows(spark)
    docs = make_docs([*ODD_TEXTS, "you fool, you FOOL! here", "the house and the house", "the"])
    results = []
    for shipped, hot in ((1 << 20, 4096), (2, 10)):
        monkeypatch.setattr(toxicity, "SHIPPED", shipped)
        monkeypatch.setattr(toxicity, "HOT", hot)
        model = toxicity.fit(rows)
        assert model.whole == (shipped > 2) and 0 < len(model.local)
        results.append(sorted((r.doc_id, round(r.score, 12), r.predicted) for r in toxicity.score_table(docs, model).collect()))
    assert results[0] == results[1] and len(results[0]) == len(ODD_TEXTS) + 3


PAGES = {
    "<article><h1>Title here</h1><p>One two &amp; three</p></article>": "Title here\n\nOne two & three",
    "<body><nav><ul><li><a href=x>Menu</a></ul></nav><article><p>Text of it.<p>More of it, <b>bold</b>.</article><footer>&copy; me</footer>": "Text of it.\n\nMore of it, bold.",
    "<main><p>Real words are here</p><div class='comments'><p>I am a reader</p></div><aside>buy</aside><form>mail me</form></main>": "Real words are here",
    "<p>" + "long text " * 30 + "</p><script>var a='</p><p>no';</script><style>p{}</style><!-- <p>no</p> -->": ("long text " * 30).strip(),
    "<div class='cookie-notice'>We use cookies</div><article class='post with-sidebar'><p>Kept\n  text</p></article>": "Kept text",
    # nothing but words and links tells these apart
    "<div><a href=a>Home</a></div><div><a href=b>All our news</a></div><div>" + "some long text of it " * 20 + "</div><div><a href=c>Next</a></div>": ("some long text of it " * 20).strip(),
    "<table><tr><td><a href=a>One</a><td><a href=b>Two</a></table><p>" + "plain words " * 40 + "<p>" + "more words " * 40: ("plain words " * 40).strip() + "\n\n" + ("more words " * 40).strip(),
    "<header><h1>Site</h1></header><section class='post'><h1>Title</h1><p>Body one two three.</p><ul><li>An item</li><li>More</li></ul><table><tr><td>cell</td></tr></table></section><section id='comments'><article><p>reader says hello</p></article></section>": "Title\n\nBody one two three.\n\nAn item\n\nMore\n\ncell",
    "<article><p>Para one is here.</p><div class='newsletter-signup'><p>Subscribe now</p></div><p class='byline'>By Me</p><div class='related-posts'><h3>More</h3><ul><li><a href=y>Other</a></li></ul></div><section class='comments'><h2>Comments</h2><p>First!</p></section></article>": "Para one is here.",
    "<article><p>Kept</p><p>Also kept <": "Kept\n\nAlso kept <",
    "": "", "<p>": "", "<script>never ends <p>x</p>": "",
}


@pytest.mark.parametrize("page", PAGES)
def test_main_text(page):
    assert htmltext.main_text(page) == PAGES[page]


def test_the_tree_decides_by_words_links_and_neighbours_and_learns_the_rest():
    own = htmltext.classifier()
    pages = htmltext.labelled_pages(200, seed=99)
    table = [htmltext.blocks(p) for p in pages]
    truth = [[htmltext.MAIN in b.text for b in found] for found in table]
    right = lambda c: sum(k == y for f, t in zip(table, truth) for k, y in zip(c.tree.predict(htmltext.features(f, c.odds)) >= 0.5, t)) / sum(map(len, truth))
    assert right(own) > 0.985
    assert own.odds["advert"] < -1 and own.odds["<article>"] > 0.5 and "unheard" not in own.odds
    # without the features of words and links the answers are worse
    x = [htmltext.features(f, own.odds) for f in table]
    for f in x:
        f[:, :6] = 0
    blind = sum((own.tree.predict(f) >= 0.5).tolist() == t for f, t in zip(x, truth))
    seen = sum((own.tree.predict(htmltext.features(f, own.odds)) >= 0.5).tolist() == t for f, t in zip(table, truth))
    assert seen > blind + 10
    # names are learned: other labelled pages, other names
    swapped = [p.replace("advert", "promenade") for p in htmltext.labelled_pages(200)]
    assert "promenade" in htmltext.fit(swapped).odds


def test_broken_pages_take_linear_time():
    for page in ("<a " * 200_000, "<div>" * 50_000 + "</p>" * 50_000 + "x", "<p class='" * 100_000, "<!--" * 100_000, "&" * 300_000):
        assert len(htmltext.main_text(page)) <= len(page)


def test_html_table(spark):
    df = spark.createDataFrame([(1, "u", None), (2, None, "<article><p>é x</p></article>")], "page_id long, url string, html string").selectExpr("*", "1 AS text")
    assert [(r.page_id, r.url, r.text, r.n_chars) for r in htmltext.extract(df).orderBy("page_id").collect()] == [(1, "u", "", 0), (2, None, "é x", 3)]
    assert htmltext.extract(df.limit(0)).count() == 0


def test_url_rules(spark):
    urls = {
        "http://A.Net/x": ("a.net", "/x", "net/", "block"), "https://example.net/en/1?q": ("example.net", "/en/1", "example.net/en/", "allow"),
        "https://b.example.net/en": ("b.example.net", "/en", "net/", "block"), "http://m.example.com/de/": ("m.example.com", "/de/", "example.com/de/", "block"),
        "http://x.org/fr/a#t": ("x.org", "/fr/a", "org/fr/", "allow"), "http://notexample.com/de/": ("notexample.com", "/de/", None, None),
        "http://net": ("net", "", None, None), "no scheme": ("", "", None, None), None: ("", "", None, None), "": ("", "", None, None),
    }
    df = spark.createDataFrame([(i, u) for i, u in enumerate(urls)] + [(0, "http://A.Net/x")], "page_id long, url string").selectExpr("*", "1 AS rule", "2 AS row")
    rows = urlfilter.judge(df).collect()
    assert len(rows) == len(urls) + 1
    for r in rows:
        host, path, rule, verdict = list(urls.values())[r.page_id]
        assert (r.host, r.path, r.rule) == (host, path, rule)
        assert r.verdict == verdict if verdict else r.verdict in ("allow", "block")
    assert urlfilter.judge(df.limit(0)).count() == 0


def test_url_ratios_are_means_over_exact_grams(spark):
    names = [hashlib.md5(str(i).encode()).hexdigest() for i in range(600)]
    urls = [f"http://h.{('net', 'org', 'edu')[i % 3]}/{('x', 'fr', 'y')[i % 3]}/{n}" for i, n in enumerate(names)]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: r for r in urlfilter.judge(df).collect()}
    ruled = urlfilter.parts(df).withColumn("ruled", urlfilter.by_rule()[1])
    learn = F.crc32(F.col("page_id").cast("string").cast("binary")) % 5 != 0
    diff = {r.gram: r.diff for r in urlfilter.differences(urlfilter.gram_counts(ruled, learn).cache()).collect()}
    for r in got.values():
        text = "\u0002" * 4 + r.host + r.path + "\u0003"
        own = [diff[text[i : i + 5]] for i in range(len(text) - 4)]
        assert r.ratio == pytest.approx(sum(own) / len(own), abs=1e-9)
