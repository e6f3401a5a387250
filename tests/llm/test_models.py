"""URL filter, toxicity, main text and personal data: held-out accuracy and edge cases."""

import math
import html
import random
import re
import zlib

import numpy as np

from regioncount.llm import gbt
from regioncount.llm import op2_url as u
from regioncount.llm import op3_toxicity as t
from regioncount.llm import op8_html as h
from regioncount.llm import op10_pii as p


def test_trees_learn_an_interaction():
    rng = np.random.default_rng(0)
    x = rng.uniform(size=(2000, 4))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.3)).astype(float)
    m = gbt.fit(x[:1500], y[:1500], trees=30, depth=3)
    assert ((m.probabilities(x[1500:]) > 0.5) == y[1500:]).mean() > 0.97


def brute_rule(url):
    if not url or "://" not in url:
        return "", "", None
    rest = url.split("://", 1)[1]
    host = re.match(r"[^/?#]*", rest)[0]
    path = re.match(r"[^?#]*", rest[len(host) :])[0]
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    fit = [(len(a + b), a + b, v) for a, b, v in u.RULES if (host == a or host.endswith("." + a)) and path.startswith(b)]
    return host, path, max(fit)[1:] if fit else None


def test_url_rules_and_verdicts(spark, messy_pages, sf_dir):
    pages = messy_pages.unionByName(spark.read.parquet(f"{sf_dir}/pages.parquet"), allowMissingColumns=True)
    rows = u.judge(pages).collect()
    assert len(rows) == pages.count()
    want = {}
    for r in pages.collect():
        want.setdefault(r.page_id, []).append(brute_rule(r.url))
    for r in rows:
        assert any((r.host, r.path) == w[:2] and r.rule == (w[2][0] if w[2] else None) and (not w[2] or r.verdict == w[2][1]) for w in want[r.page_id])
        assert r.rule or r.verdict == ("block" if r.score >= 0.5 else "allow")
    assert u.judge(pages.limit(0)).count() == 0


def test_url_trees_on_unseen_hosts():
    rng = random.Random(1)
    word = lambda: "".join(rng.choice("aeiostnrlth") for _ in range(7))
    good = [f"https://{rng.choice(['www.', '', 'blog.'])}{word()}.example.org/en/{rng.randint(1, 9999)}" for _ in range(500)]
    bad = [f"http://{a}-{b}.example.net/{rng.randint(1, 9999)}?ref={rng.randint(1, 99)}" for a in ("casino", "cheap", "free") for b in ("win", "bets") for _ in range(40)]
    m = u.train(good + bad, [0] * len(good) + [1] * len(bad))
    unseen = [f"http://poker-{word()}.example.net/{k}?ref=3" for k in range(30)]
    assert (m.scores(unseen) >= 0.5).mean() > 0.9 and (m.scores([f"https://{word()}.example.org/en/{k}" for k in range(50)]) < 0.5).mean() > 0.9
    assert (u.train(good, [0] * len(good)).scores(bad) == 0).all()


def corpus(n, seed):
    rng = random.Random(seed)
    vocab = ["".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(2, 9))) for _ in range(800)]
    insults = ["idiot", "moron", "pathetic", "worthless", "scumbag"]
    texts, labels = [], []
    for k in range(n):
        w = [rng.choice(vocab) for _ in range(rng.choice([12, 60, 300]))]
        toxic = k % 3 == 0
        if toxic:
            for _ in range(max(1, len(w) // 50)):
                w[rng.randrange(len(w))] = rng.choice(insults)
        texts.append(" ".join(w))
        labels.append(int(toxic))
    return texts, labels


def naive_buckets(word):
    """The n-grams of one word by plain integers."""
    w, low, odd = b"<" + word.encode() + b">", 2**64 - 1, 0x9E3779B97F4A7C15
    codes = [int.from_bytes(w[i : i + n], "little") + (n << 40) for n in (3, 4, 5) for i in range(len(w) - n + 1)]
    codes.append(sum((c + 1) * pow(odd, k + 1, 2**64) for k, c in enumerate(w)) & low)
    return [((c * odd) & low) >> (64 - t.BITS) for c in codes]


def naive_score(m, text):
    """The score by loops over windows and words."""
    words = text.lower().split()
    if not words:
        logit = m.bias - 10
    else:
        starts = list(range(0, len(words), 12))
        if len(starts) > 1 and len(words) - starts[-1] < 6:
            starts.pop()
        each = []
        for a, b in zip(starts, [*starts[1:], len(words)], strict=True):
            value = [float(np.mean([m.weight[g] for g in naive_buckets(t.core(w))])) for w in set(words[a:b])]
            each.append(sum(value) / max(12, len(value)))
        logit = max(each) + m.bias
    return 1 / (1 + math.exp(-min(30, max(-30, logit - m.threshold))))


def test_toxicity_learns_and_shares_misspellings():
    texts, labels = corpus(900, 3)
    m = t.train(texts[:700], labels[:700], updates=150)
    guess = m.scorer().scores(texts[700:]) >= 0.5
    assert np.mean([g == bool(y) for g, y in zip(guess, labels[700:], strict=True)]) > 0.95
    a, b, c = t.word_values(m.weight, ["idiiot", "bakelmo", "mooron"])
    assert a > 5 * abs(b) and c > 0
    assert m.scorer().scores([""])[0] < 0.01
    assert t.train(["a b", "c d"], [0, 0]).scorer().scores(["idiot"])[0] < 0.5


def test_toxicity_scores_against_a_naive_scorer(monkeypatch):
    rng = np.random.default_rng(5)
    m = t.Model(rng.normal(size=t.BUCKETS), 0.3, 0.1)
    draw = random.Random(6)
    words = ["idiot", "Ünïcode", "(a)", "<b>", "--", "漢字", "x" * 300, "the", "the,", "\x00", "e\u0301"] + ["".join(draw.choice("abcdeé") for _ in range(draw.randint(1, 12))) for _ in range(80)]
    texts = ["", " \n", "one"] + [" ".join(draw.choice(words) for _ in range(n)) for n in [*range(1, 60), 500, 3000]]
    monkeypatch.setattr(t, "CACHE_ENTRIES", 30)
    scorer = m.scorer()
    for _ in range(2):
        got = np.concatenate([scorer.scores(texts[:20]), scorer.scores(texts[20:])])
        assert np.allclose(got, [naive_score(m, x) for x in texts], atol=1e-9)


def test_toxicity_table(spark, messy, no_documents):
    texts, labels = corpus(300, 5)
    docs = messy.select("doc_id", "text", "score").union(spark.createDataFrame([(1000 + k, x, "c") for k, x in enumerate(texts)], "doc_id long, text string, score string"))
    marks = spark.createDataFrame([(1000 + k, None, y) for k, y in enumerate(labels)] + [(3, 1, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    used, _ = t.labelled_sample(docs, marks, 5000)
    by_text = {x: 1000 + k for k, x in enumerate(texts)}
    assert used and all(zlib.crc32(str(by_text[x]).encode()) % 5 for x in used) and len(t.labelled_sample(docs, marks, 10)[0]) == 30
    rows = t.score_documents(docs, marks).collect()
    assert len(rows) == docs.count() and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in rows)
    assert all(r.held_out == (zlib.crc32(("" if r.doc_id is None else str(r.doc_id)).encode()) % 5 == 0) for r in rows)
    kept = t.keep_clean(docs, marks)
    assert kept.columns == docs.columns and kept.count() == sum(r.score < 0.5 for r in rows)
    assert t.score_documents(no_documents, marks).count() == 0 and t.score_documents(docs, marks.limit(0)).count() == docs.count()


def test_main_text_on_unseen_layouts():
    m, rng, right = h.train(), random.Random(123), 0
    for _ in range(200):
        source = h.make_page(rng)
        page, state = h.labelled(source)
        right += m.texts([source.replace(" data-m", "")])[0] == h.assemble(page, list(state))
    assert right >= 192
    assert m.texts(["", None, "plain &amp; text", "<p>a<p>b"]) == ["", "", "plain & text", "a\nb"]


def test_nesting_alone_loses_nothing():
    m = h.train()
    prose = "First paragraph, with some words in it. And a second sentence."
    shell = "<html><body><nav><ul><li><a href=/>Home</a></li><li><a href=/a>News</a></li></ul></nav>{}<footer>Copyright of somebody.</footer></body></html>"
    for wrap in ("<div>{}</div>", "<div><hr>{}</div>", "<section class=col>{}</section>", "<div><div></div>{}</div>", "<span>{}</span>", "<div>{}<p></p></div>"):
        before, after = wrap.split("{}")
        for depth in (1, 10, 15, 100, 3000):
            inside = before * depth + f"<p>{prose}</p>" + after * depth
            assert m.texts([inside, shell.format(inside + "<p>Another one follows.</p>")]) == [prose, f"{prose}\nAnother one follows."], (wrap, depth)
    assert m.texts(["<div>" * 3000 + "deep", "<div>" * 20_000 + "</b>" * 20_000 + "deep"]) == ["deep", "deep"]


def test_wrappers_collapse_and_keep_boundaries():
    p = h.parse("a<div><div><p>b</p></div></div>c<div class=footer><p>d</p></div>")
    assert p.tag == ["#root", "p", "div", "p"] and p.parent == [-1, 0, 0, 2]
    assert h.assemble(p, [h.ARTICLE] * 4) == "a\nb\nc\nd"


def test_main_text_states_do_not_contradict():
    rng = np.random.default_rng(2)
    for seed in range(30):
        page = h.parse(h.make_page(random.Random(seed)))
        n = len(page.tag)
        a = rng.uniform(size=n)
        state = h.decode(page, a * 0.9, (1 - a) * rng.uniform(size=n))
        for k in range(1, n):
            up = state[page.parent[k]]
            assert up == h.CONTAINER or state[k] in ((h.ARTICLE, h.BOILER) if up == h.ARTICLE else (h.BOILER,))


def test_main_text_table(spark, messy_pages, sf_dir):
    m = h.train(300)
    rows = h.extract(messy_pages, m).collect()
    assert len(rows) == messy_pages.count() and all(r.n_chars == len(r.text) for r in rows)
    assert {r.page_id: r.text for r in h.extract(messy_pages).collect()} == {1: "a\nb", 2: "", 3: "", 4: "deep", 5: "plain & text", None: "x"}
    assert h.extract(messy_pages.limit(0), m).count() == 0
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    for r in h.extract(pages, h.train()).join(pages.select("page_id", "html"), "page_id").collect():
        inner = re.search(r"(?s)<article>(.*?)</article>", r.html)[1]
        blocks = [" ".join(html.unescape(re.sub(r"<[^>]*>", " ", b)).split()) for b in re.split(r"</?(?:p|h1)[^>]*>", inner)]
        assert r.text == "\n".join(b for b in blocks if b)
    # the same without the telling tag: nearly all pages as before
    sources = [r.html for r in pages.select("html").collect()]
    plain = [re.sub(r"(</?)article>", r"\1div>", x) for x in sources]
    full = h.train()
    assert sum(a != b for a, b in zip(full.texts(sources), full.texts(plain), strict=True)) <= len(sources) // 50


def brute_base(text):
    out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m[0].split("."))]
    out += [("card", *m.span()) for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text) if 16 <= sum(c.isdigit() for c in m[0]) <= 19 and p.luhn(re.sub(r"\D", "", m[0]))]
    return out + [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 8 <= sum(c.isdigit() for c in m[0]) <= 15]


def test_base_spans_against_plain_patterns():
    rng = random.Random(9)
    for _ in range(4000):
        text = "".join(rng.choice("0123456789.@+ -()abA%é\n") for _ in range(60))
        assert p.base_spans(text) == brute_base(text)


def test_field_on_unseen_sentences():
    w = p.train()
    hit = wrong = missed = 0
    for text, spans in p.sentences(300, seed=41):
        got = set(p.decode(text, w))
        hit, wrong, missed = hit + len(got & set(spans)), wrong + len(got - set(spans)), missed + len(set(spans) - got)
    assert hit > 0.97 * (hit + missed) and hit > 0.97 * (hit + wrong)


def test_best_segmentation_against_brute_force():
    rng = np.random.default_rng(4)
    text = "call 555-123-4567 now 4111 1111"
    toks = p.tokens(text)
    for _ in range(5):
        w = rng.normal(size=(len(p.FEATURES), len(p.KINDS)))
        score = {(i, j): float(w[f].sum(axis=0).max()) for i, j, f in p.segments(toks, text)}

        def best(j, score=score):
            return 0.0 if j == 0 else max([best(j - 1)] + [best(i) + s for (i, e), s in score.items() if e == j])

        index = {(toks[i][1], toks[j - 1][2]): (i, j) for i, j in score}
        assert np.isclose(sum(score[index[s, e]] for _, s, e in p.decode(text, w)), best(len(toks)))


def test_personal_data_table(spark, messy, no_documents):
    w = p.train(300, 60)
    rows = p.find(messy, w).collect()
    assert len(rows) == messy.count() and p.find(no_documents, w).count() == 0
    nine = next(r for r in rows if r.doc_id == 9)
    assert (nine.n_email, nine.n_phone, nine.spans) == (1, 1, "email:5:31,phone:35:52")
    clean = p.redact_documents(messy, w)
    assert clean.columns == messy.columns and clean.count() == messy.count()
    by_id = {r.doc_id: r for r in clean.collect()}
    assert by_id[9].text == "mail [EMAIL] or [PHONE]" and by_id[9].n_chars == 23 and by_id[3].text is None
    assert by_id[1].text == "One two three four five six seven."
    assert p.mask("abcdef", [("ip", 1, 4), ("card", 2, 5)]) == "a[IP]f"


def test_stretches_decode_as_the_whole_text():
    field = p.train()
    names = "write to jane at example.com|call 555-123-4567|mail bob@example.com|see you at noon. Bye|x at y|at|.|dot|jane [at] example [dot] com|jane at example dot com|٣٣٣-٣٣٣-٣٣٣٣|²²²² ²²²²|phone|card|4111 1111 1111 1111|10.0.0.1|_at_|fax:|12|a.b.c|contact john.smith at home|1a2b".split("|")
    rng = random.Random(11)
    plain = "we wrote to jane at example.com about the plan"
    assert p.decode(plain, field) and not re.search(r"[0-9@]|dot", plain)
    texts = [plain, f"phone {'.' * 70} 555-123-4567", "jane at " + "a-" * 60 + "b.example.com", "at" * 50_000, "1 " * 20_000, "1a" * 2_000, ""]
    for _ in range(300):
        words = [rng.choice(names) if rng.random() < 0.3 else rng.choice(["word", "many", "longer-than-others", "x"]) for _ in range(rng.randint(1, 90))]
        texts.append("".join(w + rng.choice([" ", " ", " ", "  ", "\n", "\t", ", ", ". "]) for w in words))
    for text in texts:
        assert [x for a, b in p.stretches(text) for x in p.decode(text, field, a, b)] == p.decode(text, field)
    assert p.written(p.all_spans(plain, field)[1]) == f"email:{plain.index('jane')}:{plain.index(' about')}"


def test_suffix_statistics_are_of_all_labelled_urls(spark, sf_dir):
    urls = [f"https://{'casino' if k % 3 else 'plain'}{k}.{'shop' if k % 2 else 'org'}/p{k}" for k in range(120)]
    pages = spark.createDataFrame([(k, x) for k, x in enumerate(urls)] + [(200, None), (201, "no scheme")], "page_id long, url string")
    labelled = u.weak_labels(pages)
    m, every = u.fit(labelled, rows=20), u.fit(labelled)
    assert m.trees is not None and m.share == every.share
    assert m.counts["org"] == every.counts["org"] == (40, 60) and m.counts["shop"] == every.counts["shop"] == (40, 60)
    for broadcast_rows in (500_000, 0):
        scored = u.with_scores(pages, m, counts=u.suffix_counts(labelled), broadcast_rows=broadcast_rows).collect()
        want = dict(zip(urls, u.Filter(m.trees, every.counts, m.share).scores(urls), strict=True))
        assert len(scored) == 122 and all(np.isclose(r.score, want[r.url]) for r in scored if r.url in want)
