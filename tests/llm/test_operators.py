"""Each operator against a brute-force version, and on odd tables."""

import collections
import math
import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from tplforge.llm import decontaminate, hashed_linear, html_extract, language_id, mixing, quality_classifier, quality_rules, simhash, substring_dedup, token_counts, url_rules
from tplforge.llm.text_features import COUNTS, count_features

WORDS = "the of river and bridge water was on two that council monday plan stone north again rise".split()
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, votes string, fp string, seed long, runs int, n_words string, kept string, rate double, stack int"


def _doc(i, text, lang="en"):
    return (i, text, lang, "src", len(text or ""), "v", "f", 1, 2, "n", "k", 0.5, 3)


def _texts(n=60, seed=4):
    rng = random.Random(seed)
    out = [" ".join(rng.choice(WORDS) + str(rng.randrange(40)) for _ in range(rng.randint(12, 90))) for _ in range(n)]
    out += [None, "", " \n\t ", "one", "tiny text", out[0], out[0], out[1] + " and more", "x" * 50_000, "lone " * 4000]
    out += [out[2][:200] + " " + out[3], out[5].replace(" ", "\n"), "***" * 30 + " " + "### $$$ " * 40]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([_doc(i, t) for i, t in enumerate(_texts())], SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


def test_counts(docs):
    for r in count_features(docs).join(docs.select("doc_id", "text"), "doc_id").collect():
        t = r["text"] or ""
        ws = t.encode().split()
        win = collections.Counter(tuple(ws[i : i + 5]) for i in range(len(ws) - 4))
        hit = {j for i in range(len(ws) - 4) if win[tuple(ws[i : i + 5])] > 1 for j in range(i, i + 5)}
        lines = [x for x in t.split("\n") if x.split()]
        want = (len(ws), sum(len(w.decode()) for w in ws), sum(t.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(hit))
        assert tuple(r[c] for c in COUNTS[:5]) == want


def test_quality_rules(docs, none):
    got = {r["doc_id"]: r for r in quality_rules.contract(docs).collect()}
    assert len(got) == docs.count()
    assert not got[60]["kept"] and got[60]["base_failed"] and got[61]["n_words"] == 0
    assert sum(got[i]["kept"] for i in range(60)) == 60
    assert quality_rules.contract(none).count() == 0
    assert quality_rules.keep_good(docs).columns == docs.columns


def test_quality_classifier(docs, none):
    got = {r["doc_id"]: r for r in quality_classifier.score(docs).collect()}
    assert len(got) == docs.count() and all(0 <= r["score"] <= 1 for r in got.values())
    assert all(got[i]["keep"] for i in range(60))
    assert quality_classifier.score(none).count() == 0


def test_token_counts(docs, none):
    import public_tokenizers
    from tokenizers import Tokenizer

    tk = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    odd = ["w\u00a0 x\u2003\u2003y \u3000z!\u00a0?", "a\x1cb !\x1d ? \x1e\x1f  q", "q" * 70 + " " + "r" * 70 + "\u00a0" + "s" * 70, "a\u00a0 b  c\n\n d ", "don't <|endoftext|> stop<|endoftext|>", "  lead", "trail  ", "tab\t\ttab", "é ü\u2003x", "a\u3000\n", "1234 5,6", "\x1c \x1f", "\U0001f600 ok"]
    more = docs.sparkSession.createDataFrame([_doc(1000 + i, t) for i, t in enumerate(odd)], SCHEMA)
    for r in token_counts.contract(docs.union(more)).join(docs.union(more).select("doc_id", "text"), "doc_id").collect():
        t = r["text"] or ""
        n = len(tk.encode(t, add_special_tokens=False))
        assert (r["n_bytes"], r["n_tokens"], r["over_limit"]) == (len(t.encode()), n, n > 512)
    assert token_counts.contract(none).count() == 0


def _judge(url, rules):
    if not url or "://" not in url:
        return "", "", None, "allow"
    rest = url.split("://", 1)[1]
    host = rest[: next((i for i, c in enumerate(rest) if c in "/?#"), len(rest))]
    path = rest[len(host) :]
    path = path[: next((i for i, c in enumerate(path) if c in "?#"), len(path))]
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    fit = [(h, p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fit, key=lambda r: (len(r[0] + r[1]), len(r[0])), default=None)
    return host, path, best and best[0] + best[1], best[2] if best else "allow"


def test_url_rules(spark):
    rng = random.Random(2)
    hosts = ["example.com", "www.Example.com", "a.b.example.com", "net", "x.net", "com", "notexample.com", "example.com.org", "", "EXAMPLE.COM:80"]
    paths = ["", "/", "/en", "/en/", "/en/x", "/es/1?q=/en/", "/fr/#a", "?x", "#y", "/deep/er/"]
    urls = [f"http://{h}{p}" for h in hosts for p in paths] + [None, "", "no scheme", "a://b://c/en/"]
    rows = [(i, u, "x", 1) for i, u in enumerate(urls * 2)]
    pages = spark.createDataFrame(rows, "page_id long, url string, host string, stack int")
    extra = [("com", "", "block"), ("b.example.com", "/e", "allow"), ("example.com", "/en/x", "block"), ("example.com", "/deep/", "block"), ("x.net", "", "allow")]
    for rules in (url_rules.RULES, (*url_rules.RULES, *extra), ()):
        got = {r["page_id"]: tuple(r)[1:] for r in url_rules.judge_urls(pages, url_rules.rule_table(spark, rules), buckets=rng.choice((1, 7))).collect()}
        assert len(got) == len(rows)
        for i, u, *_ in rows:
            assert got[i] == _judge(u, rules), u
    assert url_rules.judge_urls(pages.limit(0), url_rules.rule_table(spark)).count() == 0


def _edits(item, text):
    row = [0] * (len(text) + 1)
    for i, c in enumerate(item, 1):
        new = [i]
        for j, x in enumerate(text, 1):
            new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (c != x)))
        row = new
    return min(row)


def test_decontamination(spark, docs):
    rng = random.Random(9)
    item = " ".join(rng.choice(WORDS) + str(rng.randrange(99)) for _ in range(20))
    items = spark.createDataFrame([(1, item), (2, None), (3, ""), (4, item), (5, "short one"), (6, "Q" * 60)], "item_id long, text string")
    e = decontaminate.budget(len(item))
    assert [decontaminate.budget(n) for n in (0, 19, 20, 39, 40)] == [0, 0, 1, 1, 2]
    rows = [(0, "x " + item.upper() + " y"), (1, "p " + item.replace("1", "7", e)), (2, item[5:]), (3, item[e + 1 :]), (4, None), (5, "a  short\n ONE b"), (6, item[: len(item) // 2])]
    d = spark.createDataFrame(rows, "doc_id long, text string").union(docs.select(F.col("doc_id") + 100, "text"))
    got = {r["doc_id"]: r for r in decontaminate.contract(d, items).collect()}
    assert set(got) == {0, 1, 2, 5}
    assert got[0]["item_ids"] == [1, 4] and got[0]["least_edits"] == 0
    for i in (1, 2):
        assert got[i]["least_edits"] == _edits(item, decontaminate.normal(rows[i][1])) > 0
    for _ in range(200):
        a, b = ("".join(rng.choice("ab c") for _ in range(rng.randint(1, 12))) for _ in range(2))
        want = _edits(a, b)
        assert decontaminate.myers(a, b, len(a)) == want
        assert (decontaminate.myers(a, b, 2) is not None) == (want <= 2)
    small = decontaminate.find_items(d, items, block_chars=10)
    assert sorted((r["doc_id"], k) for r in small.collect() for k in r["items"]) == sorted((r["doc_id"], k) for r in got.values() for k in r["item_ids"])
    assert decontaminate.contract(d, items.limit(0)).count() == 0 and decontaminate.contract(d.limit(0), items).count() == 0
    assert decontaminate.drop_contaminated(docs, items).columns == docs.columns


def test_html_extraction(spark):
    gold = "<article><h1>Wide  &amp; far</h1><p>One <b>two</b>three<br>four.</p><ul><li>five</li></ul></article>"
    page = f'<html><head><title>t</title><script>var a="<p>no</p>"</script></head><body><nav><a href="/">Home</a></nav><div class="ad">Buy now, it is cheap.</div>{gold}<div class="comments"><p>I was there and saw all of it.</p></div><footer>Terms apply to all.</footer></body></html>'
    deep = "<div>" * 5000 + "<article><p>deep text here.</p></article>"
    rows = [(1, "u", page), (2, "u", None), (3, "u", ""), (4, None, "<article><p>open <p>a < b"), (5, "u", deep), (1, "u", page)]
    p = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, text string")
    got = collections.defaultdict(list)
    for r in html_extract.extract(p).collect():
        got[r["page_id"]].append((r["text"], r["n_chars"]))
    want = "Wide & far\nOne twothree four.\nfive"
    assert got[1] == [(want, len(want))] * 2
    assert got[2] == got[3] == [("", 0)]
    assert got[4][0][0] == "open\na < b"
    assert "deep text here." in got[5][0][0]
    assert html_extract.extract(p.limit(0)).count() == 0


def test_html_marginals_are_exact():
    m = html_extract.fit(html_extract.labelled_pages())
    t = html_extract.parse("<body><nav><a>x</a></nav><article><p>some words here.</p></article></body>")
    n = len(t.tag)
    total, on = 0.0, np.zeros(n)
    for state in range(1 << n):
        s = [state >> i & 1 for i in range(n)]
        lp = m.root[s[0]] + sum(m.move[s[t.parent[i]]][s[i]] for i in range(1, n))
        lp += sum(e[s[i]] for i in range(n) for f in t.seen[i] if (e := m.evidence(f)))
        w = math.exp(lp)
        total += w
        on += w * np.array(s)
    assert m.marginals(t) == pytest.approx((on / total).tolist(), abs=1e-9)


def test_layouts_never_trained_on():
    """Pages of other seeds: nearly all come out as they were marked, and hardly a word too many or too few."""
    m = html_extract.fit(html_extract.labelled_pages())
    exact = both = found = wanted = 0
    for seed in range(50_000, 50_200):
        page = html_extract.varied_page(seed)
        t = html_extract.parse(page)
        want = html_extract.rendered(t, [float(x) for x in html_extract.states(t)])
        got = html_extract.main_text(html_extract.unmarked(page), m)
        exact += got == want
        g, w = collections.Counter(got.split()), collections.Counter(want.split())
        both, found, wanted = both + (g & w).total(), found + g.total(), wanted + w.total()
    assert exact >= 180 and both >= 0.98 * found and both >= 0.98 * wanted


def test_pages_by_hand():
    m = html_extract.fit(html_extract.labelled_pages())
    say, more = "It rained for the third day in the hills, and the river rose again.", "No one was hurt, said the mayor."
    cases = {
        f"<article><p>Before.</p><noscript>Enable scripts to read this.</noscript><object>A plan of it.</object><p>So <math><mi>x</mi><mo>=</mo><mn>4</mn></math> holds.</p><p>{say}</p></article>": f"Before.\nA plan of it.\nSo x=4 holds.\n{say}",
        f"<body><nav><a href='/'>Home</a></nav><article><h1>Links</h1><p>{say}</p><ul><li><a href='/a'>First piece</a></li><li><a href='/b'>Second piece</a></li></ul></article><footer>Terms</footer></body>": f"Links\n{say}\nFirst piece\nSecond piece",
        f"<body><div id='x7'><h2>Rain</h2><p>{say}</p><p>{more}</p></div><div class='menu'><a href='/'>Home</a> <a href='/a'>All</a></div></body>": f"Rain\n{say}\n{more}",
        f"<table><tr><td><a href='/'>Home</a><br><a href='/n'>News</a></td><td><h2>Rain</h2><p>{say}</p></td></tr></table>": f"Rain\n{say}",
        f"<p>{say}</p>": say,
    }
    for page, want in cases.items():
        assert html_extract.main_text(page, m) == want


def test_given_pages(spark):
    """The article element of every given page, read by another parser."""
    from html.parser import HTMLParser

    class Article(HTMLParser):
        def __init__(self):
            super().__init__()
            self.inside, self.blocks = 0, [""]

        def handle_starttag(self, tag, attrs):
            self.inside += tag == "article"
            self.blocks += [""] if tag in html_extract.BLOCK else []
            self.blocks[-1] += " " if tag == "br" else ""

        def handle_endtag(self, tag):
            self.inside -= tag == "article"
            self.blocks += [""] if tag in html_extract.BLOCK else []

        def handle_data(self, data):
            self.blocks[-1] += data if self.inside > 0 else ""

    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    got = {r["page_id"]: r["text"] for r in html_extract.extract(pages).collect()}
    for r in pages.collect():
        a = Article()
        a.feed(r["html"] or "")
        assert got[r["page_id"]] == "\n".join(x for x in (" ".join(b.split()) for b in a.blocks) if x)


def test_substring_dedup(docs, none):
    rows = [(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect()]
    got = sorted(map(tuple, substring_dedup.contract(docs).collect()))
    assert got == sorted(substring_dedup.brute_force(rows))
    assert any(r[2] for r in got)
    rng = random.Random(8)
    rows = [(i, " ".join(rng.choice("ab") for _ in range(rng.randint(0, 40)))) for i in range(60)]
    d = docs.sparkSession.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r["doc_id"], r["n_words"], r["n_removed"], r["kept_text"]) for r in substring_dedup.dedup(d, window=6, gram=3).collect())
    want = substring_dedup.brute_force(rows, 6)
    import hashlib

    assert [(a, b, c, hashlib.sha256(t.encode()).hexdigest()) for a, b, c, t in got] == sorted(want)
    assert substring_dedup.contract(none).count() == 0
    assert substring_dedup.cut_repeats(docs).columns == docs.columns


def test_factors_point_at_equal_text(docs):
    text = {r["doc_id"]: (r["text"] or "").split() for r in docs.select("doc_id", "text").collect()}
    seen = 0
    for r in substring_dedup.dedup(docs).select("doc_id", "factors").collect():
        for f in r["factors"]:
            a, b = text[r["doc_id"]], text[f["src_id"]]
            assert a[f["start"] : f["start"] + f["length"]] == b[f["src_start"] : f["src_start"] + f["length"]] and f["length"] >= 20
            seen += 1
    assert seen


def test_language_id(spark):
    rng = random.Random(6)
    vocab = {"en": "the river water was bridge and again over stone".split(), "de": "der fluss wasser war brücke und wieder über stein".split()}
    rows = [(i, " ".join(rng.choice(vocab[x]) for _ in range(8)), x) for i in range(120) for x in [("en", "de")[i % 2]]]
    d = spark.createDataFrame([(*r, "z") for r in [*rows, (500, None, "en"), (501, "12 ?", "de"), (502, "", None), (503, "flüssen brücken", None), (504, "Der,Fluss", None)]], "doc_id long, text string, lang string, lang_pred string")
    got = {r["doc_id"]: r for r in language_id.contract(d).collect()}
    assert all(got[i]["lang_pred"] == x for i, _, x in rows)
    assert [got[i]["lang_pred"] for i in (500, 501, 502, 503, 504)] == ["und", "und", "und", "de", "de"]
    assert all(0 <= r["score"] <= 1 for r in got.values()) and got[500]["score"] == 0
    assert language_id.contract(d.limit(0)).count() == 0
    assert {r["lang_pred"] for r in language_id.identify(d, d.limit(0)).collect()} == {"und"}
    odd = spark.createDataFrame([(1, "\u00b2 \u00bd \u2460 \u2167"), (2, "der \u00b2"), (None, "stein"), (4, "stein " * 30_000)], "doc_id int, text string").withColumn("lang", F.lit(None).cast("string"))
    got = {r["doc_id"]: r for r in language_id.identify(odd, d).collect()}
    assert got[1]["lang_pred"] == "und" and got[1]["score"] == 0 and [got[i]["lang_pred"] for i in (2, None, 4)] == ["de"] * 3


def test_language_scores_by_hand(spark):
    """Every text's score worked out again, word by word, from counts of the training rows."""
    rng = random.Random(12)
    alphabet = {"a": "abcdé", "b": "bcdeü", "c": "cdefß"}
    rows = [(i, " ".join("".join(rng.choice(alphabet[x]) for _ in range(rng.randint(1, 4))) for _ in range(12)) + " 12 x_", x) for i in range(90) for x in ["abc"[i % 3]]]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    import zlib

    words = collections.defaultdict(collections.Counter)
    for i, t, x in rows:
        if zlib.crc32(str(i).encode()) % 4 != 2:
            words[x].update(w for w in t.replace("x_", "x").split() if w.isalpha())
    langs, all_words = sorted(words), collections.Counter()
    for c in words.values():
        all_words.update(c)

    def logs(tables, key):
        return [math.log((t[key] + 0.05) / (sum(t.values()) + 1)) for t in tables]

    grams = {}
    for n in range(1, 5):
        grams[n] = []
        for x in langs:
            c = collections.Counter()
            for w, k in words[x].items():
                for i in range(len(w) + 3 - n):
                    c[f"<{w}>"[i : i + n]] += k
            grams[n].append(c)

    def score(w):
        if all_words[w] >= 3:
            return logs([words[x] for x in langs], w)
        for n in range(4, 0, -1):
            hits = [g for i in range(len(w) + 3 - n) if any(t[(g := f"<{w}>"[i : i + n])] for t in grams[n])]
            if hits:
                return [sum(v) / len(hits) - 0.5 * (5 - n) for v in zip(*(logs(grams[n], g) for g in hits), strict=True)]
        return [0.0] * len(langs)

    unseen = 0
    for r in language_id.contract(d).join(d.select("doc_id", "text"), "doc_id").collect():
        ws = [w for w in r["text"].replace("x_", "x").split() if w.isalpha()]
        unseen += sum(all_words[w] < 3 for w in ws)
        total = [sum(v) for v in zip(*map(score, ws), strict=True)]
        best = max(total)
        assert r["lang_pred"] == langs[total.index(best)]
        assert r["score"] == pytest.approx(1 / sum(math.exp(v - best) for v in total), abs=1e-6)
    assert unseen > 20


def test_language_on_rows_never_learnt_from(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = language_id.contract(d).filter("held_out").join(d.filter("text IS NOT NULL").select("doc_id", "lang"), "doc_id")
    n, right = got.count(), got.filter("lang = lang_pred").count()
    assert n > 150 and right >= 0.98 * n


def _brute_components(fps, ids, k=4):
    label = list(range(len(fps)))
    for i in range(len(fps)):
        for j in range(i):
            if bin(int(fps[i]) ^ int(fps[j])).count("1") <= k and label[i] != label[j]:
                a, b = label[i], label[j]
                label = [a if x == b else x for x in label]
    least = {}
    for x, i in zip(label, ids, strict=True):
        least[x] = min(i, least.get(x, i))
    return [least[x] for x in label]


def _fingerprint(text):
    ws = "".join(c.lower() if "A" <= c <= "Z" else c for c in (text or "")).encode().split()
    sh = [b" ".join(ws[i : i + 4]) for i in range(len(ws) - 3)] if len(ws) >= 4 else [b" ".join(ws)] if ws else []
    h = [xxhash.xxh64_intdigest(x, 42) for x in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def test_simhash(docs, none):
    rows = [(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").orderBy("doc_id").collect()]
    fps = [_fingerprint(t) for _, t in rows]
    want = [(i, f"{f:016x}", c) for (i, _), f, c in zip(rows, fps, _brute_components(fps, [i for i, _ in rows]), strict=True)]
    assert sorted(tuple(r) for r in simhash.contract(docs).collect()) == want
    assert simhash.contract(none).count() == 0
    assert simhash.keep_one(docs).columns == docs.columns


def test_large_subtrees_are_dealt(spark):
    """Subtrees cut by their next bits into pairs of nodes give the components of all pairs."""
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    fp = base[rng.integers(0, 40, 900)]
    for _ in range(6):
        fp = fp ^ np.where(rng.random(900) < 0.5, np.uint64(1) << rng.integers(0, 64, 900).astype(np.uint64), np.uint64(0))
    fp = np.unique(fp)
    fps = spark.createDataFrame([(x, i) for i, x in enumerate(fp.view(np.int64).tolist())], "fp long, rep long")
    want = _brute_components(fp.tolist(), list(range(len(fp))))
    from tplforge.llm.components import components

    for limit in (3, 40, None):
        found = {r["node"]: r["label"] for r in components(simhash.near_links(fps, 4, limit)).collect()}
        assert [found.get(i, i) for i in range(len(fp))] == want


def test_tries_find_what_pairs_find():
    rng = np.random.default_rng(3)
    for n, centres, flips in ((400, 5, 7), (300, 300, 3), (500, 1, 9)):
        base = rng.integers(0, 1 << 63, centres, dtype=np.uint64)
        fp = base[rng.integers(0, centres, n)]
        for _ in range(flips):
            fp = fp ^ np.where(rng.random(n) < 0.5, np.uint64(1) << rng.integers(0, 64, n).astype(np.uint64), np.uint64(0))
        fp = np.unique(fp)
        rng.shuffle(fp)
        root = simhash.trie_components(fp, 4)
        want = _brute_components(fp.tolist(), list(range(len(fp))))
        groups = lambda x: sorted(map(tuple, {k: [i for i, v in enumerate(x) if v == k] for k in x}.values()))
        assert groups(root.tolist()) == groups(want)


def test_mixing(spark, docs, none):
    rows = [(i, int(i % 4 != 0), int(i % 7 == 0)) for i in range(60)]
    labels = spark.createDataFrame([*rows, (999, 1, 0), (None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")
    got = mixing.contract(docs, labels)
    assert got.count() == docs.count()
    for r in got.collect():
        assert 0 <= r["rate"] <= mixing.CEILING
        assert r["n_copies"] == 1 if abs(r["rate"] - 1) <= mixing.NEAR else r["n_copies"] in (math.floor(r["rate"]), math.floor(r["rate"]) + 1)
        assert r["p_good"] + r["p_poor"] + r["p_toxic"] == pytest.approx(1, abs=1e-5)
    assert mixing.contract(none, labels).count() == 0
    assert mixing.contract(docs, labels.limit(0)).count() == docs.count()
    assert set(docs.columns) < set(mixing.apply_mix(docs, labels).columns)


def _scored(spark, n=400, seed=1, shares=(1, 1, 1)):
    rng, names, rows = random.Random(seed), ["p_good", "p_poor", "p_toxic"], []
    for i in range(n):
        p = [w * rng.random() ** 3 for w in shares]
        rows.append((i, rng.randint(0, 300), *(x / sum(p) for x in p)))
    cells = hashed_linear.lattice(np.array([r[2:] for r in rows]), 64)
    return spark.createDataFrame([(*r, int(c)) for r, c in zip(rows, cells, strict=True)], "doc_id long, n_words long, p_good double, p_poor double, p_toxic double, cell long"), names


def _descent(fit, rows, names, pull=mixing.PULL, rounds=30_000):
    """The same problem with a rate for every document's cell, by plain gradient steps over documents."""
    n, p = np.array([r["n_words"] for r in rows], float), np.array([[r[x] for x in names] for r in rows])
    cells, at = np.unique([r["cell"] for r in rows], return_inverse=True)
    weight = np.bincount(at, n)
    mean = np.stack([np.bincount(at, n * p[:, k]) for k in range(3)], axis=1) / np.maximum(weight, 1e-9)[:, None]
    rate = np.ones(len(cells))
    for _ in range(rounds):
        total = (rate[at] * n) @ p
        gap = (total - fit.target) / n.sum()
        rate = np.clip(rate - 0.9 * (mean @ gap + pull * (rate - 1)), 0, mixing.CEILING)
    return cells, rate, weight


@pytest.mark.parametrize("weights", [(0.5, 0.3, 0.2), (0.6, 0.4, 0.0)])
def test_rates_are_the_optimum(spark, weights):
    scored, names = _scored(spark)
    rows = scored.collect()
    fit = mixing.fit_rates(scored, weights)
    assert all(b <= a + 1e-12 for a, b in zip(fit.loss, fit.loss[1:], strict=False))
    cells, rate, weight = _descent(fit, rows, names)
    assert cells.tolist() == fit.cell.tolist()
    assert fit.rate[weight > 0] == pytest.approx(rate[weight > 0], abs=2e-3)
    of = dict(zip(fit.cell.tolist(), fit.rate.tolist(), strict=True))
    assert [sum(of[r["cell"]] * r["n_words"] * r[x] for r in rows) for x in names] == pytest.approx(fit.total.tolist())
    if weights[2]:
        assert fit.total == pytest.approx(fit.target, rel=2e-2)
    else:
        assert fit.total[2] < 0.3 * fit.begun[2]
        assert all(of[r["cell"]] > 0.9 for r in rows if r["p_toxic"] < 0.01) and all(of[r["cell"]] < 0.1 for r in rows if r["p_toxic"] > 0.8)


def test_an_almost_empty_domain_drives_nothing(spark):
    """A domain that holds next to nothing is asked for what it can give, and leaves the others alone."""
    scored, names = _scored(spark, shares=(1, 1e-7, 0.02))
    fit = mixing.fit_rates(scored)
    assert fit.unreachable[1] > 0 and fit.target[1] == pytest.approx(mixing.CEILING * fit.begun[1])
    assert fit.rate.max() <= mixing.CEILING and fit.total[2] < fit.begun[2]
    good = [r["cell"] for r in scored.filter("p_toxic < 0.01").collect()]
    of = dict(zip(fit.cell.tolist(), fit.rate.tolist(), strict=True))
    assert good and all(0.9 < of[c] < 1.5 for c in good)


def test_lattice():
    rng = np.random.default_rng(2)
    p = rng.dirichlet([0.3] * 4, 500)
    p[:3] = [[1, 0, 0, 0], [0.25] * 4, [0, 0.5, 0.5, 0]]
    cell = hashed_linear.lattice(p, 10)
    point = np.stack([cell // 11**k % 11 for k in range(4)], axis=1)
    assert (point.sum(axis=1) == 10).all() and np.abs(point / 10 - p).max() < 0.1
    assert mixing.lattice_steps(3) == 64 and mixing.lattice_steps(20) < 10


def test_scorer_learns_shapes():
    good, bad = ["a plain line of words here again"] * 30, ["WORD!! WORD!! LOUD!! LOUD!!"] * 30
    raw = [t.encode() for t in good + bad]
    y = np.array([[0, 1]] * 30 + [[1, 0]] * 30, float)
    m = hashed_linear.fit(hashed_linear.features(raw)[:3], y)
    p, words = m.posteriors([b"other plain text in lower letters", b"NOISE!! NOISE!! MORE!!", b""])
    assert p[0, 1] > 0.5 > p[1, 1] and words.tolist() == [6, 3, 0]


def test_features_of_words_one_by_one():
    """Presence, shapes and word counts against a plain loop over words."""
    raw = [(t or "").encode() for t in _texts()] + ["Été 12ab #x# x# Ab aB ABC ab, (ab) AB".encode(), b"### ab ab ab"]
    d, f, v, counts = hashed_linear.features(raw, 0.5)
    for i, t in enumerate(raw):
        words = t.split()
        assert counts[i] == len(words)
        mine = d == i
        bare = ["".join(chr(c) for c in w.lower() if chr(c).isalnum() and c < 128 or c >= 128) for w in words]
        present = f[mine & (f < hashed_linear.HALF)]
        assert len(present) == len(set(present.tolist())) and len(present) <= len(set(bare) - {""}) and bool(len(present)) == any(bare)
        shares = dict(zip((f[mine] - (hashed_linear.DIMS - len(hashed_linear.SHAPES))).tolist(), v[mine].tolist(), strict=True))
        shares = {hashed_linear.SHAPES[k]: x for k, x in shares.items() if k >= 0}
        assert ("short_text" in shares) == (len(words) < 10)
        echo = sum(a == b != "" for a, b in zip(bare, bare[1:], strict=False))
        assert shares.get("echo", 0) == pytest.approx(6.0 * echo / max(1, len(words)), abs=1e-5)


def test_word_hashes():
    from tplforge.llm.common import hash_words

    rng = random.Random(3)
    raw = [" ".join("".join(rng.choice("abAB\u00e9") for _ in range(rng.choice((1, 3, 7, 8, 9, 16, 17, 600)))) for _ in range(rng.randint(0, 30))).encode() for _ in range(80)]
    raw += [b"", b" \t", b"\x0b\x0cx\x1cy\xc2\xa0z", b"a" * 5000]
    for lower in (False, True):
        h, counts = hash_words(raw, lower)
        words = [(w.lower() if lower else w) for t in raw for w in t.split()]
        assert counts.tolist() == [len(t.split()) for t in raw]
        seen = {}
        assert all(seen.setdefault(w, x) == x for w, x in zip(words, h.tolist(), strict=True)) and len(set(seen.values())) == len(seen)
