"""The ten operators on small fixtures: brute force, round trips, held-out accuracy and odd inputs."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict
from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from softdep.llm import _text, chat, decontaminate, graph, html, jaccard, lm, mixing, quality, queries, toxicity, urls, warc

DOCS = "doc_id long, text string, lang string, source string, kept string, copy string, grp string"
BLANK = r"[\x20\x09-\x0D]+"


def words_of(text):
    return [w for w in re.split(BLANK, re.sub("[A-Z]", lambda m: m[0].lower(), text or "")) if w]


def made(rng, n, vocabulary=400):
    return " ".join(f"w{min(int(rng.expovariate(1 / 60)), vocabulary)}" for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty, blank, short and very long texts, repeated rows, columns of clashing names."""
    rng = random.Random(2)
    long = made(rng, 30_000)
    rows = [
        (1, None, "en", "a", "x", "y", "z"),
        (2, "", None, None, None, None, None),
        (3, " \t\n\x0b ", "en", "a", None, None, None),
        (4, "one two three", "XX!", "b", "x", "y", "z"),
        (5, long, "en", "a", "x", "y", "z"),
        (6, long + " tail", "en", "a", "x", "y", "z"),
        (7, "Line one here\nline two\nLine one here\n\n", "de", "b", "x", "y", "z"),
        (7, "Line one here\nline two\nLine one here\n\n", "de", "b", "x", "y", "z"),
        (8, "***** ### $$$ éÉ\u00a0x <|im_end|>", "fr", "a", "x", "y", "z"),
    ]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (4, None, None), (5, 0, 1), (5, 1, 0), (99, 1, 1), (None, 1, 1)], "doc_id long, quality int, toxic int")


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


# Text kernels.


def test_words_and_hashes():
    texts = ["", None, " a\tb\x0bé  ", "a b", "\u00a0", "x" * 5, "A"]
    got = []
    for first, data, offs in _text.pieces(pa.array(texts)):
        row, start, end = _text.spans(data, offs)
        h = _text.word_hashes(data, start, end)
        got += [(int(r) + first, bytes(data[a:b]).decode(), int(x)) for r, a, b, x in zip(row, start, end, h, strict=True)]
    assert [(r, w) for r, w, _ in got] == [(i, w) for i, t in enumerate(texts) for w in re.split(BLANK, t or "") if w]
    by = defaultdict(set)
    for _, w, x in got:
        by[w].add(x)
    assert all(len(x) == 1 for x in by.values()) and len({next(iter(x)) for x in by.values()}) == len(by)


def test_slices_of_arrow_columns_are_read_right():
    column = pa.array(["zero", "one two", None, "three"]).slice(1)
    assert [len(s) for s in jaccard.sets_of(column, 2)] == [1, 0, 1]


# 1 Quality rules.


def naive_counts(text):
    t = text or ""
    w = [x for x in re.split(BLANK, t) if x]
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    seen = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {j for i in range(len(w) - 4) if seen[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    return (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered))


def test_quality_counts_against_loops(spark, odd):
    rng = random.Random(4)
    more = [(100 + i, " ".join(rng.choice("ab") for _ in range(rng.randrange(40))), "en", "a", None, None, None) for i in range(40)]
    docs = odd.union(spark.createDataFrame(more, DOCS))
    for r in quality.measured(docs).collect():
        assert tuple(r[c] for c in quality.BASE) == naive_counts(r["text"])
        assert r["base_failed"] == (r["n_words"] < 10 or 100 * r["n_repeat_words"] > 20 * r["n_words"])


def test_binomial_tail_is_exact(spark):
    cases = [(0, 10), (3, 10), (10, 10), (0, 0), (5, 2000), (40, 2000)]
    got = spark.createDataFrame(cases, "k long, n long").select("k", "n", quality.binomial_tail("k", "n", 0.0125).alias("p")).collect()
    for r in got:
        want = sum(math.comb(r["n"], j) * 0.0125**j * 0.9875 ** (r["n"] - j) for j in range(r["k"] + 1))
        assert r["p"] == pytest.approx(min(1.0, want), rel=1e-9)


def test_cutoffs_limit_false_rejection(spark):
    """Rates of good documents under 0.1, of bad ones over 0.5: certified cutoffs split them; a small stratum has none."""
    rng = random.Random(1)
    rows = [(i, "en" if i < 3000 else "fr", rng.random() * (0.09 if i % 5 else 1)) for i in range(3040)]
    feats = spark.createDataFrame(rows, "doc_id long, stratum string, symbol_rate double").select("*", *(F.lit(0.0).alias(r) for r in quality.GRIDS if r != "symbol_rate"), F.lit(False).alias("base_failed"))
    marks = spark.createDataFrame([(i, 1 if i % 5 else 0) for i in range(3040)], "doc_id long, quality int")
    cut = {(r["stratum"], r["rule"]): r for r in quality.certified(feats, marks).collect()}
    assert cut[("en", "symbol_rate")]["cutoff"] == 0.1 and cut[("fr", "symbol_rate")]["cutoff"] is None
    judged = quality.judged(feats, quality.certified(feats, marks))
    lost = judged.join(marks.where("quality = 1"), "doc_id").agg(F.avg((~F.col("kept")).cast("double"))).first()[0]
    assert lost <= 0.05 and judged.where("not kept").count() > 300


def test_quality_on_odd_rows(odd, labels, empty):
    feats = quality.measured(odd)
    out = quality.judged(feats, quality.certified(feats, labels)).collect()
    assert len(out) == 9 and all(isinstance(r["kept"], bool) for r in out)
    assert {r["doc_id"]: r["stratum"] for r in out}[4] == "other"
    feats = quality.measured(empty)
    assert quality.judged(feats, quality.certified(feats, labels)).count() == 0


# 2 Toxicity.


def toxic_corpus(spark, n=600):
    rng = random.Random(9)
    docs, marks = [], []
    for i in range(n):
        bad = i % 8 == 0
        text = made(rng, 80) + (" " + rng.choice(["slurone", "slurtwo,", "SLURTHREE"]) if bad else "") + " " + made(rng, 10)
        docs.append((i, text))
        if i % 2 == 0:
            marks.append((i, 1, int(bad)))
    return spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(marks, "doc_id long, quality int, toxic int")


def test_toxicity_held_out_accuracy(spark):
    docs, marks = toxic_corpus(spark)
    model = toxicity.fit(docs, marks)
    out = docs.select("doc_id", (~toxicity.in_training(F.col("doc_id"))).alias("h"), toxicity.scored(model, F.col("text")).alias("s")).collect()
    assert {r["doc_id"] for r in out if r["h"]} == {i for i in range(600) if zlib.crc32(str(i).encode()) % 5 == 0}
    held = [(r["s"] >= 0.5) == (r["doc_id"] % 8 == 0) for r in out if r["h"]]
    assert sum(held) / len(held) > 0.97
    # Labels of the held-out fold are never read.
    flipped = marks.withColumn("toxic", F.when(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    again = toxicity.fit(docs, flipped)
    assert (again.words == model.words).all() and np.allclose(again.weights, model.weights)


def test_toxicity_counts_words_of_all_rows(spark):
    """No cap on the words, and a word's frequency is that of all training rows, not of the fit's sample."""
    rng = random.Random(4)
    docs = [(i, f"{made(rng, 10)} {i % 300:03d}slur") for i in range(2700)] + [(i, f"{made(rng, 10)} fine") for i in range(2700, 11_700)]
    d = spark.createDataFrame(docs, "doc_id long, text string")
    marks = spark.createDataFrame([(i, int(i < 2700)) for i in range(11_700)], "doc_id long, toxic int")
    model = toxicity.fit(d, marks, min_g2=3.0, steps=20)
    assert len(model.words) > 256
    n, u = toxicity.row_frequency(d.select("text"), np.sort(decontaminate.words_of("fine other")))
    assert n == 11_700 and sorted(u) == [0, 9000]
    assert (model.score(pa.array([f"{i:03d}slur" for i in range(300)])) >= 0.5).mean() > 0.9


def sparse(x):
    return toxicity.Sparse(*np.nonzero(x), x.shape)


def test_non_negative_risk_on_toy_data():
    """One feature tells positives, one tells others, one tells nothing: weights of both signs."""
    rng = np.random.default_rng(0)
    pos = (rng.random((400, 3)) < [0.9, 0.5, 0.05]).astype(float)
    unl = (rng.random((4000, 3)) < np.where(rng.random((4000, 1)) < 0.2, [0.9, 0.5, 0.05], [0.02, 0.5, 0.6])).astype(float)
    w = toxicity.fit_weights(sparse(pos), lambda w: toxicity.Side.of(sparse(unl), w), 0.2, steps=200)
    assert w[0] > 2 and abs(w[1]) < 1.5 and w[2] < -1 and w[-1] < 0.5


def test_risk_and_gradient_against_sums_and_differences(spark):
    """The sums that a pass over a table gives, the risk written out term by term, and its gradient by differences."""
    rng = np.random.default_rng(1)
    pos, unl = (rng.random((30, 6)) < 0.4).astype(float), (rng.random((200, 6)) < 0.3).astype(float)
    w = rng.standard_normal(7)
    rows = spark.createDataFrame([([int(k) for k in np.flatnonzero(x)],) for x in unl], "w array<int>").repartition(3)
    passed = toxicity.summed(rows, 6)(w)
    share = np.append(pos.mean(axis=0), 1.0)

    def naive(w):
        loss = lambda z: math.log(1 + math.exp(-z))
        g = lambda x: float(x @ w[:-1] + w[-1])
        away = sum(loss(-g(x)) for x in unl) / len(unl) - 0.2 * sum(loss(-g(x)) for x in pos) / len(pos)
        return 0.2 * sum(loss(g(x)) for x in pos) / len(pos) + away, away

    value, away, grad, down = toxicity.risk(toxicity.Side.of(sparse(pos), w), passed, share, float(share @ w), 0.2)
    assert (value, away) == pytest.approx(naive(w))
    for k in range(7):
        e = np.zeros(7)
        e[k] = 1e-6
        up, low = naive(w + e), naive(w - e)
        assert grad[k] == pytest.approx((up[0] - low[0]) / 2e-6, abs=1e-6) and down[k] == pytest.approx((up[1] - low[1]) / 2e-6, abs=1e-6)


def test_frequent_words_are_all_named(spark):
    """Whatever the batches and partitions: a word in a tenth of all rows is named, also if it comes late or early only."""
    rng = random.Random(3)
    docs = [f"{'early ' if i < 150 else ''}{'late ' if i > 850 else ''}{'rare ' if i % 50 == 0 else ''}x{rng.randrange(10**6)}" for i in range(1000)]
    for parts in (1, 7):
        got = set(toxicity.frequent(spark.createDataFrame([(d,) for d in docs], "t string").repartition(parts), 0.1).tolist())
        named = lambda w: int(decontaminate.words_of(w)[0]) in got
        assert named("early") and named("late") and not (parts == 1 and named("rare"))


def test_toxicity_on_odd_rows(odd, labels, empty):
    model = toxicity.fit(odd, labels)
    scores = [r[0] for r in odd.select(toxicity.scored(model, F.col("text"))).collect()]
    assert len(scores) == 9 and all(0 <= s <= 1 for s in scores)
    assert toxicity.fit(empty, labels).score(pa.array(["x", None, ""])).shape == (3,)
    assert toxicity.fit(odd, labels.limit(0)).prior == 0


# 3 Chat.


def forest_of(spark, rows):
    return chat.forest(spark.createDataFrame(rows, "tree string, id long, parent long, score double, role string, text string"))


def test_reply_trees_against_recursion(spark):
    rng = random.Random(6)
    rows = []
    for t in ("a", "b", None):
        for i in range(60):
            rows.append((t, i, rng.randrange(i) if i else None, rng.random(), rng.choice(["user", "assistant", None]), f"m{i}"))
    rows += [("a", 100, 101, 1.0, "user", "cycle"), ("a", 101, 100, 1.0, "user", "cycle"), ("b", 200, 999, 0.5, "user", "orphan"), ("c", 1, 1, 0.1, "user", "self")]
    f = forest_of(spark, rows)
    by = defaultdict(dict)
    for t, i, p, s, *_ in rows:
        by[t][i] = (p if p != i and p in {x[1] for x in rows if x[0] == t} else None, s)

    def path(t, i):
        out = []
        while i is not None and i not in out:
            out.append(i)
            i = by[t][i][0]
        return out[::-1] if i is None else None

    leaves = {t: [i for i in m if i not in {p for p, _ in m.values()}] for t, m in by.items()}
    all_branches = {(r["tree"], r["leaf"]): r for r in chat.branches(f, None).collect()}
    want = {(t, i): path(t, i) for t in by for i in leaves[t] if path(t, i)}
    assert set(all_branches) == set(want)
    for (t, i), p in want.items():
        assert all_branches[(t, i)]["depth"] == len(p)
        assert all_branches[(t, i)]["score"] == pytest.approx(sum(by[t][x][1] for x in p) / len(p))
    got = defaultdict(list)
    for r in chat.paths(f, chat.branches(f, 2)).collect():
        got[(r["tree"], r["leaf"])].append((r["pos"], int(r["text"][1:]) if r["text"].startswith("m") else r["text"]))
    for k, v in got.items():
        if k[0] is not None and k[1] < 100 and k[0] != "c":
            assert [x for _, x in sorted(v)] == want[k]
    assert {r["id"] for r in chat.rootless(f).collect()} == {100, 101}


def test_round_trip_of_control_strings(spark):
    texts = ["", None, "<|im_end|>", "<\\|x", "<|<\\\\|>|", "a\nb<|im_start|>assistant\nhi", "\\n", "end<", "|im_end|>", "<|im_end|>\n<|im_start|>user\n", "é😀<|"]
    roles = ["user", "assistant", "ass\\nist", "<|im_end|>", "a\nb", "", None, "assistant", "x\\", "\\\n", "assistant"]
    rows = spark.createDataFrame([(1, i, r, t) for i, (r, t) in enumerate(zip(roles, texts, strict=True))], "conv_id long, turn long, role string, text string")
    f = chat.forest(chat.conversations(rows))
    out = chat.formatted(chat.paths(f, chat.branches(f)))
    r = out.select("formatted", "loss_spans", chat.read_turns(F.col("formatted")).alias("t"), chat.read_loss(F.col("formatted"), F.col("loss_spans")).alias("l")).first()
    assert [(t["role"], t["text"]) for t in r["t"]] == [(a or "", b or "") for a, b in zip(roles, texts, strict=True)]
    assert r["l"] == "".join(b or "" for a, b in zip(roles, texts, strict=True) if a == "assistant")
    assert r["formatted"].count("<|im_start|>") == len(texts)


def test_chat_query_and_ties(spark, sf):
    got = {r["conv_id"]: r for r in queries.op3_chat_formatting(spark, sf).collect()}
    rows = spark.read.parquet(f"{sf}/conversations.parquet").orderBy("conv_id", "turn").collect()
    by = defaultdict(list)
    for r in rows:
        by[r["conv_id"]].append(r)
    assert set(got) == set(by) | {-1} and got[-1]["n_turns"] == 2
    for k, v in by.items():
        assert got[k]["turns_sha256"] == hashlib.sha256("".join(f"{r['role']}\n{r['text']}\n" for r in v).encode()).hexdigest()
    same = spark.createDataFrame([(1, 0, "user", "a")] * 3 + [(None, None, None, None)], "conv_id long, turn long, role string, text string")
    f = chat.forest(chat.conversations(same))
    assert sorted(r["n"] for r in chat.paths(f, chat.branches(f)).groupBy("tree").agg(F.count("*").alias("n")).collect()) == [1, 3]
    none = chat.forest(chat.conversations(same.limit(0)))
    assert chat.formatted(chat.paths(none, chat.branches(none))).count() == 0


# 4 HTML.

PAGE = """<html><head><title>T</title><style>p{}</style><script>var a='</p>';</script></head><body>
<header><h1>Site</h1></header><nav><ul><li><a href=x>Menu</a></ul></nav><div class="cookie-notice">We use cookies</div>
<main><article><h1>Title &amp; more</h1><p>First   <b>bold</b>
text<br>goes on.<p>Second &lt;par&gt; caf&eacute; &#x41;<div class="ad-box">Buy</div><form><input>Search</form>
<ul><li>one<li>two</ul><section class="comments"><article class="comment"><p>Nice!</p></article></section></article></main>
<aside>Side</aside><footer>&copy; x</footer><!-- hidden --></body></html>"""


def test_main_text_of_a_page():
    assert html.main_text(PAGE) == "Title & more\n\nFirst bold text goes on.\n\nSecond <par> café A\n\none\n\ntwo"


@pytest.mark.parametrize("bad", [None, "", "<", "<p", "</p></div>", "<p>a<p>b</i>", "&#xZZ; &bogus;", "<script>never closed", "<!-- open", "plain text", "<a href='>'>x</a>", "<p hidden>no</p>"])
def test_broken_markup(bad):
    assert isinstance(html.main_text(bad), str)


def test_style_tree_finds_unnamed_boilerplate(spark):
    """No telling tag or class: only the entropies tell the box that repeats from the text that does not."""
    page = lambda i: f"<body><div class=xa><p>Same words in each page</p></div><div class=xb><p>Own text number {i} here</p></div></body>"
    rows = [(i, f"http://h.org/{i}", page(i)) for i in range(30)] + [(100, "http://solo.org/1", page(7)), (101, None, None), (102, "no host", "")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("noise", F.lit(1)).withColumn("host", F.lit("c"))
    imp = {r["path"]: r for r in html.node_importance(html.page_trees(pages)).where("host = 'h.org'").collect()}
    assert imp["/body/div.xa/p"]["importance"] < 0.01 < 0.99 < imp["/body/div.xb/p"]["importance"]
    got = {r["page_id"]: r["text"] for r in html.extracted(pages).collect()}
    assert got[3] == "Own text number 3 here" and "Same words" in got[100] and got[101] == got[102] == ""
    far = {r["page_id"]: r["text"] for r in html.extracted(pages, max_broadcast_rows=-1).collect()}
    assert far == got
    assert html.extracted(pages.limit(0)).count() == 0
    twins = spark.createDataFrame([(i, "http://t.org/x", page(1)) for i in range(9)], "page_id long, url string, html string")
    assert {r["text"] for r in html.extracted(twins).collect()} == {"Same words in each page\n\nOwn text number 1 here"}


def test_the_tree_decides_inside_articles_and_out(spark):
    """Boilerplate without a telling name beside and inside the article. Without the tree all of it would stay; what varies
    stays with it. Importance against the formula written out."""
    page = lambda i: f"<html><body><div class=qa><p>Top {'ab'[i % 2]}</p></div><article><h1>Title {i}</h1><p>Body {i}</p><div class=qb><p>Read us each day</p></div></article></body></html>"
    loose = lambda i: page(i).replace("article>", "div>").replace("<article", "<div")
    rows = [(i, "http://a.org/x", page(i)) for i in range(8)] + [(100 + i, "http://b.org/x", loose(i)) for i in range(8)] + [(200, "http://c.org/x", page(0))]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in html.extracted(pages).collect()}
    assert got[3] == "Title 3\n\nBody 3" and got[103] == "Title 3\n\nBody 3" and got[200] == "Title 0\n\nBody 0\n\nRead us each day"
    bare = {r["page_id"]: r["text"] for r in html.extracted(pages, min_pages=99).collect()}
    assert bare[3] == "Title 3\n\nBody 3\n\nRead us each day" and bare[103] == "Top b\n\nTitle 3\n\nBody 3\n\nRead us each day"
    imp = {r["path"]: r["importance"] for r in html.node_importance(html.page_trees(pages)).where("host = 'a.org'").collect()}
    assert imp["/html/body/div.qa/p"] == pytest.approx(1 - math.log(4) / math.log(8)) and imp["/html/body/article/p"] == pytest.approx(1)
    for i, _, x in rows[:8]:
        assert html.main_text(x, frozenset(p for p, v in imp.items() if v < 0.1 and "qb" in p)) == got[i]


# 5 Jaccard join.


def brute_classes(docs, size=5, percent=80):
    sets = {}
    for k, t in docs:
        w = words_of(t)
        sets[k] = frozenset(tuple(w[i : i + size]) for i in range(len(w) - size + 1)) if len(w) >= size else frozenset([tuple(w)] if w else [])
    parent = {k: k for k in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    return {k: (len(s), find(k)) for k, s in sets.items()}


def copies(rng, n_families=6, members=14, length=80):
    """Families whose members are edited to land on both sides of the limit, with a passage that all documents share."""
    passage, out = made(rng, 30), []
    for _ in range(n_families):
        base = made(rng, length, 10_000).split()
        for _ in range(members):
            w = base[:]
            for _ in range(rng.randrange(5)):
                w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
            out.append(" ".join(w) + (" " + passage if rng.random() < 0.6 else ""))
    out += [out[0], out[0].upper(), passage, passage + " x", "a b", "a b", "A  B", "", " "]
    rng.shuffle(out)
    return list(enumerate(out))


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_jaccard_against_all_pairs(spark, seed):
    docs = copies(random.Random(seed), length=60 + 30 * seed)
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(5)
    got = {r["key"]: (r["n_shingles"], r["component_id"]) for r in jaccard.classes(df, chunk_chars=3000).collect()}
    assert got == brute_classes(docs)


def test_matrix_alone_loses_no_link(spark):
    """One star with a single centre leaves the rest to the groups."""
    docs = copies(random.Random(8), n_families=3, members=30, length=50)
    probed = jaccard.probes(spark.createDataFrame(docs, "doc_id long, text string"), chunk_chars=2000)
    got = {r["id"]: r["component"] for r in jaccard.linked(probed, jaccard.named(probed), stars=(1,), group_size=4).collect()}
    sets = {r["key"]: (r["n"], r["s1"], r["s2"]) for r in probed.collect()}
    low = {}
    for k in sorted(sets):
        low.setdefault(sets[k], k)
    want = brute_classes(docs)
    assert all(got.get(low[s], low[s]) == want[low[s]][1] for s in low if s[0])


def test_jaccard_on_odd_rows(odd, empty):
    got = {r["key"]: (r["n_shingles"], r["component_id"]) for r in jaccard.classes(odd).collect()}
    assert got == brute_classes([(r["doc_id"], r["text"]) for r in odd.collect()])
    assert jaccard.classes(empty).count() == 0


@pytest.mark.parametrize("kind", ["long", "string"])
def test_rows_without_ids_keep_links(spark, kind):
    """A copy without an id beside one with, its near copy, and a text without any id between two that link by it alone."""
    w = [f"t{k}" for k in range(100)]
    near = [*w[:-3], "x", "y", "z"]
    mid = [f"m{k}" for k in range(100)]
    left, right = [*(f"l{k}" for k in range(9)), *mid[9:]], [*mid[:-9], *(f"r{k}" for k in range(9))]
    rows = [(None, w), (3, w), (5, near), (8, left), (None, mid), (9, right), (7, ["u", "v"])]
    cast = (lambda k: k) if kind == "long" else (lambda k: None if k is None else str(k))
    docs = spark.createDataFrame([(cast(k), " ".join(t)) for k, t in rows], f"doc_id {kind}, text string")
    got = {r["key"]: r["component_id"] for r in jaccard.classes(docs).where("key is not null").collect()}
    assert got == {cast(k): cast(v) for k, v in {3: 3, 5: 3, 7: 7, 8: 8, 9: 8}.items()}


def test_one_id_with_unlike_texts(spark):
    """Each row has the component of its own text; a component is named by the smallest id in it."""
    w = [f"t{k}" for k in range(60)]
    near = [*w[:-2], "x", "y"]
    rows = [(5, " ".join(w)), (5, "entirely other words in this text"), (9, " ".join(near)), (7, "entirely other words in this text"), (5, " ".join(w)), (6, None)]
    out = jaccard.members(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    by = {(r["key"], r["n_shingles"]): r for r in out}
    assert len(out) == 5 and by[(5, 56)]["times"] == 2
    assert by[(5, 56)]["component"] == by[(9, 56)]["component"] != by[(5, 2)]["component"] == by[(7, 2)]["component"]
    assert {r["component_id"] for r in out} == {5, 6} and by[(6, 0)]["component"] is None
    assert len(jaccard.classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()) == 6


def test_components_against_union_find(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(150)] + [(i, i + 1) for i in range(300, 380)]
    got = {r["id"]: r["component"] for r in graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    parent = {x: x for e in edges for x in e if e[0] != e[1]}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a != b:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    assert got == {x: find(x) for x in parent}


# 6 Mixing.


def test_quantiles_and_mean(spark):
    from math import exp, factorial

    cdf = spark.range(1).select(mixing.quantiles(F.lit(1.7)).alias("c")).first()["c"]
    assert cdf[3] == pytest.approx(sum(exp(-1.7) * 1.7**k / factorial(k) for k in range(4))) and cdf[-1] == pytest.approx(1.0)
    big = spark.range(1).select(mixing.quantiles(F.lit(900.0)).alias("c")).first()["c"]
    assert big[-1] == pytest.approx(1.0, abs=1e-9) and big == sorted(big)


def test_mix_reaches_its_weights(spark):
    rows = [(i, "x" * (5 + i % 7), "big" if i % 3 else "small") for i in range(9000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    rates = mixing.rates(docs, {"big": 1.0, "small": 3.0}, epochs=2.0)
    out = mixing.replicated(docs, rates, seed=5)
    by = {r["source"]: r["n"] for r in out.groupBy("source").agg(F.sum(F.length("text")).alias("n")).collect()}
    whole = sum(len(t) for _, t, _ in rows)
    assert sum(by.values()) == pytest.approx(2 * whole, rel=0.03) and by["small"] / by["big"] == pytest.approx(3, rel=0.05)
    again = mixing.replicated(docs.repartition(7), rates, seed=5, max_broadcast_sources=0)
    key = lambda d: sorted((r["doc_id"], r["copy"], r["shuffle_key"]) for r in d.select("doc_id", "copy", "shuffle_key").collect())
    assert key(out) == key(again) and len(set(key(out))) == out.count()
    first = [r["doc_id"] for r in out.select("doc_id").limit(200).collect()]
    assert first != sorted(first)


def test_mix_on_odd_rows(odd, empty):
    out = mixing.replicated(odd, mixing.rates(odd, {"a": 1.0, "b": 0.0}, size=F.lit(1)))
    assert {r["source"] for r in out.select("source").distinct().collect()} <= {"a", None} and "copy" in out.columns
    assert mixing.replicated(empty, mixing.rates(empty, {})).count() == 0


def test_native_operators_run_no_python(spark, sf):
    for name in ("op1_quality_rules", "op6_poisson_mixing"):
        plan = queries.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Arrow|Pandas", plan)


# 7 Decontamination.


def test_bit_parallel_subsequence():
    rng = random.Random(0)
    for _ in range(200):
        a, b = ([rng.randrange(6) for _ in range(rng.randrange(1, 90))] for _ in "ab")
        row = [0] * (len(b) + 1)
        for x in a:
            last = 0
            for j, y in enumerate(b):
                last, row[j + 1] = row[j + 1], last + 1 if x == y else max(row[j + 1], row[j])
        assert decontaminate.common_words(np.array(a, np.uint64), np.array(b, np.uint64)) == row[-1]


def leaky(rng):
    items = [(i, made(rng, rng.randrange(15, 60), 9000).replace("w", f"q{i}w", 8)) for i in range(30)]
    docs, truth = [], set()
    for d in range(300):
        body = made(rng, rng.randrange(20, 400), 9000).split()
        if d % 6 == 0:
            i = d // 6 % 30
            w = items[i][1].split()
            if d % 12 == 0:  # paraphrase: every eighth word changed, one dropped
                w = [x if k % 8 else f"z{k}" for k, x in enumerate(w)]
                del w[len(w) // 2]
            at = rng.randrange(len(body))
            body[at:at] = w
            truth.add((d, i))
        elif d % 6 == 1:  # a decoy: a quarter of an item
            w = items[d % 30][1].split()
            body[5:5] = w[: len(w) // 4]
        docs.append((d, " ".join(body)))
    return items, docs, truth


def test_leaks_found_and_decoys_left(spark):
    items, docs, truth = leaky(random.Random(12))
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r["key"], r["item_id"]) for r in decontaminate.leaks(d, b).collect()}
    assert got == truth
    assert {(r["key"], r["item_id"]) for r in decontaminate.leaks(d, b, block_items=7).collect()} == truth
    assert {r["doc_id"] for r in decontaminate.clean(d, b).collect()} == {k for k, _ in docs} - {k for k, _ in truth}


def test_leaks_of_common_words_are_found_whatever_the_space(spark):
    """Items of common words beside many of rare ones, in a space of few dimensions: whole and with a fifth or a quarter changed."""
    rng = random.Random(5)
    common = [(i, " ".join(f"c{rng.randrange(40)}" for _ in range(20))) for i in range(12)]
    rare = [(100 + i, " ".join(f"r{i}x{k}" for k in range(30))) for i in range(60)]
    docs, truth = [], set()
    for d in range(120):
        body = [f"c{rng.randrange(40)}" if rng.random() < 0.7 else f"r{rng.randrange(60)}x{rng.randrange(30)}" for _ in range(200)]
        if d % 2 == 0:
            i = d // 2 % 12
            w = common[i][1].split()
            for k in rng.sample(range(20), (0, 4, 5)[d // 2 % 3]):
                w[k] = f"z{k}"
            at = rng.randrange(len(body))
            body[at:at] = w
        docs.append((d, " ".join(body)))
        text = [decontaminate.words_of(x) for x in (docs[-1][1], *(w for _, w in common))]
        for i, item in enumerate(text[1:]):
            parts = [text[0][x : x + 25] for x in range(max(1, len(text[0]) - 24))]
            if any((c := decontaminate.common_words(item, p)) >= 16 or (c >= 13 and decontaminate.common_words(item[-5:], p) >= 4) for p in parts):
                truth.add((d, i))
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(common + rare, "item_id long, text string")
    got = {(r["key"], r["item_id"]) for r in decontaminate.leaks(d, b, rank=8).collect()}
    assert len(truth) >= 40 and truth <= got
    assert {r["doc_id"] for r in decontaminate.clean(d, b, rank=8).collect()} <= {k for k, _ in docs} - {k for k, _ in truth}


def test_short_items_match_where_all_their_words_stand_in_a_row(spark):
    items = [(1, "zig zag zog"), (2, "lone"), (3, "two words"), (4, "Zag, zog! zig zag"), (5, ""), (6, "zig zag zog")]
    texts = ["a zig zag zog b", "zig zag x zog", "lone", "a lone wolf", "Two Words.", "those two words", "zig\nZAG zog; zig zag", None]
    d, b = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    want = {(k, i) for k, t in enumerate(texts) for i, x in items for w, v in [(re.findall(r"\w+", (t or "").lower()), re.findall(r"\w+", x.lower()))] if v and (w == v if len(v) < 3 else any(w[j : j + len(v)] == v for j in range(len(w))))}
    got = [(r["key"], r["item_id"], r["first_word"], r["end_word"]) for r in decontaminate.leaks(d, b).collect()]
    assert {x[:2] for x in got} == want and {(0, 1), (0, 6), (2, 2), (4, 3), (6, 4)} <= want
    assert next(x[2:] for x in got if x[:2] == (0, 1)) == (1, 4)
    long = spark.createDataFrame([*items, (9, " ".join(f"w{k}" for k in range(20)))], "item_id long, text string")
    assert {(r["key"], r["item_id"]) for r in decontaminate.leaks(d, long).collect()} == want
    assert {r["doc_id"] for r in decontaminate.clean(d, b).collect()} == set(range(8)) - {k for k, _ in want}


def test_leaks_are_those_of_a_search_of_every_stretch(spark):
    """Brute force: every stretch of a quarter more than the item's length. It must hold all that is found by the same rule
    on stretches twice as long, and all it finds must be found."""
    items, docs, _ = leaky(random.Random(31))
    items, docs = items[:12], docs[:80]
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r["key"], r["item_id"]) for r in decontaminate.leaks(d, b).collect()}

    def leaks(k, i, factor):
        text, item = (decontaminate.words_of(x) for x in (docs[k][1], items[i][1]))
        n, size = len(item), int(len(item) * factor)
        answer = item[-max(3, n // 4) :]
        for x in range(max(1, len(text) - size + 1)):
            c = decontaminate.common_words(item, text[x : x + size]) / n
            if c >= 0.8 or (c >= 0.65 and decontaminate.common_words(answer, text[x : x + size]) / len(answer) >= 0.65):
                return True
        return False

    pairs = [(k, i) for k in range(len(docs)) for i in range(len(items))]
    narrow, wide = {x for x in pairs if leaks(*x, 1.25)}, {x for x in pairs if x in got and leaks(*x, 1.5)}
    assert narrow and narrow <= got and got == wide


def test_random_projection_finds_the_singular_space(spark):
    rng = random.Random(3)
    items = decontaminate.Items.of([(i, made(rng, 40, 300), None) for i in range(40)], 8, 36)
    terms = np.unique(np.concatenate(items.words))
    idf = np.ones(len(terms))
    v = decontaminate.latent_space(spark, items, terms, idf, 8)
    a = np.zeros((len(items.passages), len(terms)))
    for k, (i, x, y) in enumerate(items.passages):
        np.add.at(a[k], np.searchsorted(terms, items.words[i][x:y]), 1.0)
    best = np.linalg.svd(a, full_matrices=False)[1][:8]
    assert np.linalg.norm(a @ v) ** 2 >= 0.93 * (best**2).sum() and np.allclose(v.T @ v, np.eye(8), atol=1e-3)


def test_leaks_on_odd_rows(spark, odd, empty):
    bench = spark.createDataFrame([(1, None), (2, ""), (3, "short item"), (None, made(random.Random(2), 30)), (4, made(random.Random(2), 30))], "item_id long, text string")
    got = {(r["key"], r["item_id"]) for r in decontaminate.leaks(odd, bench).collect()}
    assert got == {(5, None), (5, 4), (6, None), (6, 4)}
    assert decontaminate.leaks(empty, bench).count() == 0 and decontaminate.leaks(odd, bench.limit(0)).count() == 0


# 8 Language model.


def test_elias_fano_against_sorted_lists():
    rng = np.random.default_rng(0)
    for n, top in ((0, 1), (1, 10), (7, 7), (1000, 10**15), (3000, 90), (2000, 2**56)):
        v = np.sort(rng.integers(0, top, n).astype(np.uint64))
        e, _ = lm.EliasFano.at(memoryview(lm.EliasFano.encoded(v)), 0)
        assert (e.get(np.arange(n)) == v).all()
        q = np.concatenate([v, rng.integers(0, top, 300).astype(np.uint64)])
        held = set(v.tolist())
        for x, i in zip(q.tolist(), e.find(q).tolist(), strict=True):
            assert (i >= 0) == (x in held) and (i < 0 or v[i] == x)


def test_codes_round_probabilities_within_a_step():
    p = np.array([0, 1e-9, 3e-7, 0.004, 0.5, 1.0])
    back = lm.probability_of(lm.code_of(p))
    assert back[0] == 0 and back[-1] == 1 and np.allclose(back, p, rtol=0.05)


def brute_lm(docs, m2, m3, quantised=True):
    learn = {k for k, _ in docs if zlib.crc32(str(k).encode()) % 5 != 1}
    tokens = {i: [*words_of(t), None] for i, (_, t) in enumerate(docs)}
    c1, c2, c3 = Counter(), Counter(), Counter()
    for i, (k, _) in enumerate(docs):
        if k in learn:
            w = tokens[i]
            c1.update(w)
            c2.update(zip(w, w[1:], strict=False))
            c3.update(zip(w, w[1:], w[2:], strict=False))
    n, v = sum(c1.values()), len(c1)
    q = (lambda p: float(lm.probability_of(lm.code_of(np.array([p])))[0])) if quantised else (lambda p: p)
    out = []
    for i, (k, _) in enumerate(docs):
        w = tokens[i]
        base = score = 0.0
        for i, x in enumerate(w):
            p1 = (c1[x] + 0.5) / (n + 0.5 * (v + 1))
            p = p1
            if i:
                p = q(c2[(w[i - 1], x)] / (c1[w[i - 1]] + m2)) + m2 / (c1[w[i - 1]] + m2) * p1
            if i > 1:
                two = c2[(w[i - 2], w[i - 1])]
                p = q(c3[(w[i - 2], w[i - 1], x)] / (two + m3)) + q(m3 / (two + m3)) * p
            base, score = base + math.log10(p1), score + math.log10(min(p, 1.0))
        out.append((k, k not in learn, len(w), sum(c1[x] > 0 for x in w), n, base, score))
    return out


def test_scores_against_counting(spark, odd):
    rng = random.Random(21)
    docs = [(i, made(rng, rng.randrange(120), 80) if i % 9 else None) for i in range(90)] + [(200 + i, "A b\tA b c") for i in range(4)]
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    got = lm.scores(df, F.crc32(F.col("key").cast("string")) % 5 != 1, m2=50.0, m3=3.0, chunk_chars=4000).collect()
    got = sorted((r["key"], not r["learn"], r["n_tokens"], r["n_known"], r["train_tokens"], r["base_score"], r["score"]) for r in got)
    for quantised in (True, False):
        want = sorted(brute_lm(docs, 50.0, 3.0, quantised))
        assert len(got) == len(want)
        for g, x in zip(got, want, strict=True):
            assert g[:5] == x[:5] and g[5] == pytest.approx(x[5])
            # Exact with the stored bytes; without them within the stated 0.042 for a token.
            assert g[6] == pytest.approx(x[6]) if quantised else abs(g[6] - x[6]) <= 0.042 * g[2]


def test_probabilities_sum_to_one_within_the_bytes():
    """Over the seen words and one unseen, as the base measure has it, for each context in the trie."""
    text = "a b a c a b b a c c a b"
    w = lm.words_of(pa.array([text]), 1)
    counts = np.bincount(w.at, minlength=len(w.words))
    g = lm.grams_of(w.row, w.at, 3, 1)
    first, last = g.pairs >> np.uint64(3), g.pairs & np.uint64(7)
    part = (first, last, np.bincount(g.pair_at), counts[first.astype(int)], g.parent, g.third, np.bincount(g.triple_at))
    trie = lm.Trie(memoryview(lm.trie_of([part], 3, 4.0, 2.0)), 3)
    for r, v in enumerate(trie.roots.get(np.arange(trie.roots.size))):
        kids = trie.children(0, r)
        assert set(kids.tolist()) == {int(b) for a, b in zip(first, last, strict=True) if a == v}
        place = trie._below(0, np.full(len(kids), r), kids)
        a2 = lm.probability_of(trie.levels[0][2][0][place])
        assert a2.sum() + 4.0 / (counts[int(v)] + 4.0) == pytest.approx(1, rel=0.05)
        for x in place:
            below = trie.children(1, int(x))
            a3 = lm.probability_of(trie.levels[1][2][0][trie._below(1, np.full(len(below), x), below)])
            assert a3.sum() + lm.probability_of(trie.levels[0][2][1][x]) == pytest.approx(1, rel=0.05) or not len(below)
            assert trie._below(1, np.array([x]), np.array([6], np.uint64))[0] == -1


def test_repeated_rows_count_and_are_dealt_once(spark):
    docs = [(1, "a b c a b"), (7, "a b d")] * 40 + [(2, "b c")]
    got = lm.scores(spark.createDataFrame(docs, "doc_id long, text string"), F.crc32(F.col("key").cast("string")) % 5 != 1).collect()
    want = brute_lm(docs, 4000.0, 10.0)
    assert sorted((r["key"], r["n_tokens"], r["train_tokens"], round(r["score"], 9)) for r in got) == sorted((x[0], x[2], x[4], round(x[6], 9)) for x in want)


def test_lm_on_odd_rows(odd, empty):
    got = lm.scores(odd, F.crc32(F.col("key").cast("string")) % 5 != 1).collect()
    assert len(got) == 9 and {r["n_tokens"] for r in got if r["key"] in (1, 2, 3)} == {1}
    assert all(r["score"] <= 0 and math.isfinite(r["score"]) for r in got)
    assert lm.scores(empty, F.lit(True)).count() == 0
    untrained = lm.scores(odd, F.lit(False)).collect()
    assert all(r["train_tokens"] == 0 and math.isfinite(r["score"]) for r in untrained)


# 9 URL rules.


def naive_glob(glob, text):
    out, i = "", 0
    while i < len(glob):
        c = glob[i : i + 1]
        if c == b"\\":
            i += 1
            out += re.escape(glob[i : i + 1].decode("latin-1"))
        else:
            out += {b"*": ".*", b"?": "[^\xff]"}.get(c, re.escape(c.decode("latin-1")))
        i += 1
    return re.fullmatch(out, text.decode("latin-1"), re.S) is not None


def test_automaton_against_regexes():
    rng = random.Random(5)
    globs = ["".join(rng.choice("ab*?\xff") for _ in range(rng.randrange(0, 9))).encode("latin-1") for _ in range(120)] + [b"", b"*", b"**", b"a\\*b", b"x" * 150 + b"*", b"?" * 70]
    texts = ["".join(rng.choice("ab\xff") for _ in range(rng.randrange(0, 12))).encode("latin-1") for _ in range(200)] + [b"", b"a*b", b"x" * 160, b"x" * 149, b"a" * 70]
    got = urls.Automaton(globs).match(texts)
    for i, t in enumerate(texts):
        for j, g in enumerate(globs):
            assert got[i, j] == naive_glob(g, t), (g, t)


def test_url_rules(spark):
    cases = [
        ("https://a.example.net/en/x", "a.example.net", "/en/x", "example.net/en/", "allow"),
        ("http://EXAMPLE.NET/de", "example.net", "/de", "net/", "block"),
        ("http://x.com/.example.net/en/", "x.com", "/.example.net/en/", None, "allow"),
        ("http://fr.org/fr/?q=1#t", "fr.org", "/fr/", "org/fr/", "allow"),
        ("http://notnet/", "notnet", "/", None, "allow"),
        ("http://net", "net", "", None, "allow"),
        ("http://m.cheap-pills.org", "m.cheap-pills.org", "", None, "block"),
        ("ftp://h.net?x://y", "h.net", "", None, "allow"),
        ("nothing", "", "", None, "allow"),
        (None, "", "", None, "allow"),
        ("", "", "", None, "allow"),
        ("http://é.net/" + "a" * 5000, "é.net", "/" + "a" * 5000, "net/", "block"),
    ]
    df = spark.createDataFrame([(i, c[0]) for i, c in enumerate(cases)], "i int, url string")
    host, path = urls.host_of(F.col("url")), urls.path_of(F.col("url"))
    got = df.select("i", host.alias("h"), path.alias("p"), urls.judged(queries.URL_RULES, host, path).alias("j")).orderBy("i").collect()
    assert [(r["h"], r["p"], r["j"]["rule"], r["j"]["verdict"]) for r in got] == [c[1:] for c in cases]
    assert df.limit(0).select(urls.judged([], host, path)).count() == 0
    assert df.limit(2).select(urls.judged([], host, path)["verdict"]).first()[0] == "allow"


# 10 Revisits.


def test_revisits_against_loops(spark):
    rng = random.Random(14)
    rows = []
    for i in range(300):
        status = rng.choice([200, 304, 304, 404])
        headers = {}
        if rng.random() < 0.7:
            headers["ETag"] = rng.choice(['"a"', 'W/"a"', '"b"'])
        if rng.random() < 0.5:
            headers["Last-Modified"] = rng.choice(["m1", "m2"])
        headers |= {"Cache-Control": f"c{i}", "X-Own": f"x{i}"}
        url = rng.choice(["http://www.H.org/a/", "https://h.org:443/a#f", "http://h.org/b?q", "broken", None])
        rows.append((i, url, rng.randrange(5000) * 60 if rng.random() < 0.97 else None, status, headers if rng.random() < 0.9 else None))
    df = spark.createDataFrame(rows, "id long, url string, s long, status int, headers map<string,string>").withColumn("ts", F.timestamp_seconds("s"))
    got = {r["id"]: r for r in warc.resolved(df, bucket_seconds=7200).collect()}
    key = {"http://www.H.org/a/": "h.org/a", "https://h.org:443/a#f": "h.org/a", "http://h.org/b?q": "h.org/b?q"}
    low = lambda h: {k.lower(): v for k, v in (h or {}).items()}
    weak = lambda e: e.removeprefix("W/")
    assert set(got) == {r[0] for r in rows if r[3] == 304}
    for i, url, s, status, h in rows:
        if status != 304:
            continue
        prior = max(((t, j) for j, u, t, st, _ in rows if st == 200 and t is not None and s is not None and t < s and key.get(u) and key.get(u) == key.get(url)), default=None)
        own, ref = low(h), low(rows[prior[1]][4]) if prior else {}
        if prior is None:
            want = "no_prior"
        elif "etag" in own and "etag" in ref:
            want = "etag" if weak(own["etag"]) == weak(ref["etag"]) else "mismatch"
        elif "last-modified" in own and "last-modified" in ref:
            want = "last_modified" if own["last-modified"] == ref["last-modified"] else "mismatch"
        else:
            want = "unvalidated"
        assert got[i]["outcome"] == want
        if want in ("no_prior", "mismatch"):
            assert got[i]["response_id"] is None and got[i]["headers"] is None
        else:
            assert got[i]["response_id"] == prior[1]
            assert got[i]["headers"] == ref | {k: v for k, v in own.items() if k in warc.PERMITTED}
    assert warc.resolved(df.limit(0)).count() == 0
    bodies = warc.with_bodies(warc.resolved(df), df.withColumn("body", F.concat(F.lit("b"), "id")))
    assert all(r["body"] == (f"b{r['response_id']}" if r["response_id"] is not None else None) for r in bodies.collect())
