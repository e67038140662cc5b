"""URL rules, toxicity, tokens, HTML, near duplicates, secrets and decontamination."""

import itertools
import random
import re
import time
import zlib

import numpy as np
import pytest

from hgpart.llm.automaton import compile_rules
from hgpart.llm.decontaminate import decontaminate, drop_contaminated
from hgpart.llm.html_text import extract_text, main_text
from hgpart.llm.ngram_join import ngram_components, shingle_sets
from hgpart.llm.queries import URL_RULES, tokenizer_path
from hgpart.llm.secrets import BASE, RULES, Scanner, scan_secrets
from hgpart.llm.tokens import Encoder, Shard, pack_shard, re_pair, token_round_trip
from hgpart.llm.toxicity import fit_arrays, fit_toxicity, score_toxicity, training_rows
from hgpart.llm.url_filter import filter_urls, mine_url_rules, split_url

DOCS = "doc_id long, text string, w string, score double"


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, "x", 0.5) for i, t in rows], DOCS)


# -- URLs


def test_listed_rules(spark):
    urls = ["http://a.com/x", "https://www.example.com/en/1", "http://m.example.com/en/1?q", "http://example.com/de/", "http://x.example.net/es/5#t", "http://x.NET/fr/", "http://x.net/en/", "http://com", "nothing", None, "http://notexample.com/en/", "http://a.net:80/es/"]
    want = [("com/", "allow"), ("www.example.com/en/", "allow"), ("example.com/en/", "block"), ("com/", "allow"), ("net/es/", "block"), ("net/fr/", "block"), (None, "allow"), (None, "allow"), (None, "allow"), (None, "allow"), ("com/", "allow"), (None, "allow")]
    pages = spark.createDataFrame([(i, u, "old") for i, u in enumerate(urls)], "page_id long, url string, rule string")
    got = filter_urls(pages, [], URL_RULES).orderBy("page_id").collect()
    assert [(r["rule"], r["verdict"]) for r in got] == want
    assert split_url("HTTP://User@Ho.ST:1/Path/X?y#z") == ("User@Ho.ST:1".lower(), "/Path/X") and split_url("a://h?x/y") == ("h", "")
    assert filter_urls(pages.limit(0), [], URL_RULES).collect() == []


def test_mined_rules(spark):
    rng = random.Random(1)
    rows = []
    for i in range(600):
        spam = rng.random() < 0.3
        rows.append((f"http://{'casino' if spam else 'news'}{'-win' if rng.random() < .5 else ''}.site{rng.randint(0, 5)}.org/{rng.choice('ab')}/{i}", int(spam)))
    mined = mine_url_rules(spark.createDataFrame(rows, "url string, blocked int"))
    assert mined and all(c >= 0.8 for _, c in mined)
    # brute force: confidence and support of every rule
    from hgpart.llm.url_filter import url_tokens

    for items, c in mined:
        hit = [y for u, y in rows if set(items) <= set(url_tokens(u))]
        assert sum(hit) / len(hit) == pytest.approx(c) and sum(hit) >= 20
    out = filter_urls(spark.createDataFrame([("http://casino.site1.org/a/9",), ("http://news.site1.org/a/9",)], "url string"), mined).collect()
    assert [r["verdict"] for r in out] == ["block", "allow"]
    none = spark.createDataFrame([("http://a.b/", 0), (None, 1), ("http://c.d/", None)], "url string, blocked int")
    assert mine_url_rules(none) == [] and mine_url_rules(none.limit(0)) == []


def test_rules_of_neutral_tokens_in_long_urls(spark):
    from hgpart.llm.url_filter import url_tokens

    rows = []
    for i in range(400):
        a, b = i % 2, i // 2 % 2
        words = ["alpha"] * a + ["beta"] * b + [f"w{j}" for j in range(7) if a == b or (i // 4 + j) % 3]
        rows.append((f"http://x.org/{'/'.join(words)}", int(a == b)))
    mined = mine_url_rules(spark.createDataFrame(rows, "url string, blocked int"))
    assert (["p:alpha", "p:beta"], 1.0) in [(sorted(x), c) for x, c in mined]
    # brute force over all sets of up to three tokens, and no shorter kept rule as sure
    sets = [(set(url_tokens(u)), y) for u, y in rows]
    kept = []
    for size in (1, 2, 3):
        for x in itertools.combinations(sorted(set().union(*(t for t, _ in sets))), size):
            hit = [y for t, y in sets if set(x) <= t]
            if hit and sum(hit) >= 20 and sum(hit) / len(hit) >= 0.8 and not any(set(k) < set(x) and c >= sum(hit) / len(hit) for k, c in kept):
                kept.append((list(x), sum(hit) / len(hit)))
    assert sorted((sorted(x), c) for x, c in mined if len(x) <= 3) == sorted(kept)


# -- toxicity


def test_toxicity_held_out(spark, sf):
    d = sf.replace("0.001", "0.01")
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = fit_toxicity(training_rows(docs, labels))
    got = score_toxicity(docs, model).toPandas().merge(labels.toPandas(), on="doc_id")
    assert (got["held_out"] == got["doc_id"].map(lambda i: zlib.crc32(str(i).encode()) % 3 == 1)).all()
    assert got["score"].between(0, 1).all() and ((got["score"] >= 0.7) == (got["predicted"] == 1)).all()
    test = got[got["held_out"]]
    hit = test[test["predicted"] == 1]
    assert len(hit) and hit["toxic"].mean() > 0.9
    rank = test["score"].rank()
    p = (test["toxic"] == 1).sum()
    assert (rank[test["toxic"] == 1].sum() - p * (p + 1) / 2) / (p * (len(test) - p)) > 0.9


def test_toxicity_edges(spark):
    model = fit_arrays(["good day", "bad idiot", "idiot you", "nice day", "fine weather", "such an idiot"] * 5, np.array([0, 1, 1, 0, 0, 1] * 5))
    rows = docs_of(spark, [(1, None), (2, ""), (None, "an idiot"), (3, "nice " * 20000)])
    got = {r["doc_id"]: r for r in score_toxicity(rows, model).collect()}
    assert got[1]["score"] == got[2]["score"] and got[None]["score"] > 0.5 > got[3]["score"]
    assert fit_arrays([], np.zeros(0)).score(["x"])[0] == pytest.approx(0.5)
    assert fit_arrays(["a", "b"], np.array([1, 1])).score([""])[0] == pytest.approx(0.75)
    labels = spark.createDataFrame([(1, 1), (1, 0), (None, 1), (2, None)], "doc_id long, toxic int")
    assert training_rows(rows, labels).collect() == []
    assert score_toxicity(rows.limit(0), model).collect() == []


# -- tokens


@pytest.fixture(scope="module")
def encoder():
    return Encoder(tokenizer_path())


def test_encoder_equals_library(encoder):
    rng = random.Random(3)
    texts = ["".join(chr(rng.choice([rng.randint(0, 300), rng.randint(32, 126), 10, 32, 32, 39, 0x85, 0xA0, 0x1D, rng.randint(0, 0xD7FF)])) for _ in range(rng.randint(0, 40))) for _ in range(2000)]
    texts += ["", " ", "a  b", "it's we'll 'tis", "a<|endoftext|>b", "x" * 9000 + " y", "\n\n x", "tail  ", "naïve café's"]
    for at in range(0, len(texts), 300):
        part = texts[at:at + 300]
        for text, ids in zip(part, encoder.encode(part)):
            assert ids.tolist() == encoder.library.encode(text, add_special_tokens=False).ids, repr(text)


def test_encoder_tells_doubling_pieces_apart(encoder):
    a, b = doubling(10)
    for texts in ([a, b], [f"x {a} y", f"x {b} y", a], ["q", b, a + "'s"]):
        assert [x.tolist() for x in encoder.encode(texts)] == [encoder.library.encode(t, add_special_tokens=False).ids for t in texts]


def test_encoder_survives_equal_hashes(encoder, monkeypatch):
    import hgpart.llm.tokens as T

    monkeypatch.setattr(T, "mix64", lambda x: x % np.uint64(3))
    one = Encoder(tokenizer_path())
    one.power = np.zeros(1 << 12, np.uint64)
    texts = ["the cat sat", "a dog ran off", "the cat", "", "mice're small"]
    assert [x.tolist() for x in one.encode(texts)] == [encoder.library.encode(t, add_special_tokens=False).ids for t in texts]


def test_re_pair_is_reversible_and_random_access():
    rng = np.random.default_rng(5)
    lengths = rng.integers(1, 400, 300)
    ids = np.concatenate([np.append(rng.integers(1, 30, n - 1), 0) for n in lengths]).astype(np.uint32)
    seq, ends, rules, after = re_pair(ids, np.cumsum(lengths), 50_257)
    assert len(seq) < 0.8 * len(ids) and len(rules) and ends[-1] == len(seq)
    shard = Shard(pack_shard(list(range(300)), lengths, ids, 50_257, 7))
    assert (shard.all_ids() == ids).all() and shard.part_start == 7
    cuts = np.concatenate([[0], np.cumsum(lengths)])
    for k in (0, 1, 150, 299):
        assert (shard.document(k) == ids[cuts[k]:cuts[k + 1]]).all()
    one = np.array([0], np.uint32)
    assert (Shard(pack_shard([None], np.array([1]), one, 50_257, 0)).all_ids() == one).all()


def test_re_pair_leaves_no_pair_twice():
    rng = np.random.default_rng(8)
    passage = rng.integers(1, 50_000, 700)
    docs = [np.append(np.concatenate([rng.integers(1, 300, rng.integers(0, 40)), passage, rng.integers(1, 300, 5)]), 0) for _ in range(60)] + [np.append(np.full(999, 7), 0), np.array([0])]
    lengths, ids = np.array([len(d) for d in docs]), np.concatenate(docs).astype(np.uint32)
    seq, ends, rules, _ = re_pair(ids, np.cumsum(lengths), 50_257)
    seen, begin = {}, 0
    for end in ends.tolist():
        last = None
        for i in range(begin, end - 1):
            pair = (int(seq[i]), int(seq[i + 1]))
            # touching occurrences in a run of one symbol count once
            last = i if pair[0] == pair[1] and last != i - 1 else None
            if pair[0] != pair[1] or last == i:
                seen[pair] = seen.get(pair, 0) + 1
        begin = end
    assert max(seen.values()) == 1 and len(seq) < 60 * 30
    assert len(np.unique(rules, axis=0)) == len(rules)
    shard = Shard(pack_shard(list(range(len(docs))), lengths, ids, 50_257, 0))
    assert (shard.all_ids() == ids).all() and (shard.document(60) == docs[60]).all()


def test_token_round_trip(spark, encoder):
    rows = [(3, "Hello world"), (1, None), (2, ""), (2, "again"), (None, "no id"), (9, "word " * 40_000), (3, "Hello world")]
    got = [tuple(r) for r in token_round_trip(docs_of(spark, rows), tokenizer_path()).orderBy("start").collect()]
    at, want = 0, []
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, (r[1] or "").encode())):
        ids = [*encoder.library.encode(t or "", add_special_tokens=False).ids, 0]
        want.append((i, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    assert got == want
    assert token_round_trip(docs_of(spark, []), tokenizer_path()).collect() == []


# -- HTML

PAGE = """<!DOCTYPE html><html><head><title>T &amp; t</title><style>p{}</style><script>var t="</p>";</script></head><body>
<nav><ul><li><a href="/a">Menu one</a><li><a href="/b">Menu two</a></ul></nav><!-- ad <p>x</p> --><div class="ad">Buy now, cheap, today.</div>
<div id="cookie-banner">We use cookies. Accept?</div><header><p>Site name</p></header>
<article><h1>Title &lt;1&gt;</h1><p><b>First   line,
with more text.<br><p>Second &copy; line<i>, joined</i> here.</p><form><input>Search</form><aside>Related</aside><ul><li>Item<li>Other</ul><p>  </p><p>Short</p>
<div class="comments"><p>Reader says hello, and more.</p></div></article><footer>&copy; site &middot; all rights, reserved.</footer></body></html>"""


def test_main_text():
    assert main_text(PAGE) == "Title <1>\nFirst line, with more text.\nSecond © line, joined here.\nItem\nOther\nShort"
    assert main_text(None) == main_text("") == main_text("<nav>x</nav>") == ""
    plain = "<body><div class='menu'>A B</div><div><p>" + "A long sentence, with commas. " * 9 + "</p><p>Tiny</p><p>" + "More text here, again. " * 9 + "</p></div><div>Imprint</div></body>"
    assert main_text(plain).split("\n")[1] == "Tiny" and "Imprint" not in main_text(plain) and "A B" not in main_text(plain)


def test_paths_choose_content_beside_articles():
    long = "<p>" + "A long sentence, with commas, and more. " * 9 + "</p>"
    teasers = "<article><h2>Read on</h2></article><article><h2>Also new</h2></article>"
    got = main_text(f"<body><div>{long}{long}</div>{teasers}</body>")
    assert got.count("A long") == 18 and "Read on" not in got and "Also new" not in got
    assert main_text(f"<body><div><h2>Head</h2>{long}{long}</div><div>Imprint</div></body>").startswith("Head\nA long")
    both = main_text(f"<body><article><h1>Title</h1>{long}</article><div>{long}</div><div>Imprint</div></body>")
    assert both.startswith("Title") and both.count("A long") == 18 and "Imprint" not in both


def test_no_share_of_the_content_is_cut():
    lead, body, close = ("<div>" + f"{w}, with commas, and a stop. " * n + "</div>" for w, n in (("Lead", 7), ("Body", 200), ("Close", 7)))
    got = main_text(f"<body>{lead}<nav>Menu</nav>{body}{close}</body>")
    assert [got.count(w) for w in ("Lead", "Body", "Close", "Menu")] == [7, 200, 7, 0]


def bare(page):
    """Without the names of furniture: only the text and where it stands are left to go by."""
    page = re.sub(r"<(/?)(nav|footer|aside|header|form|main|section|button|menu)\b[^>]*>", lambda m: f"<{m[1]}div>", page or "")
    return re.sub(r"<(div|p|ul|li|span|section|article)\s[^>]*>", r"<\1>", page)


def test_weights_decide(sf, monkeypatch):
    """By brute force over spelled-out paths, the same blocks; with equal weights, others, where no name gives furniture away."""
    import math

    import pyarrow.parquet as pq

    import hgpart.llm.html_text as H

    pages = pq.read_table(f"{sf}/pages.parquet")["html"].to_pylist()
    long = "<p>" + "A long sentence, with commas, and more. " * 9 + "</p>"
    pages += [PAGE, f"<body><div>{long}</div><article><h2>Read on</h2></article><div>Imprint</div></body>", f"<main><h1>T</h1>{long}</main><ul><li>a<li>b, c</ul>"]

    pages = [x for p in pages for x in (p, bare(p))]

    def spelled(r, path):
        return () if path <= 0 else (*spelled(r, r.above[path]), path)

    changed = 0
    for page in pages:
        r = H.Page(page)
        texts = [(t, p) for t, p in r.blocks if not r.furniture[p]]
        weight = {}
        for path in {p for _, p in texts}:
            steps = spelled(r, path)
            named = next((x for x in steps if r.section[x] == x), None)
            near = named or (steps[-2] if len(steps) > 1 else None)

            def mean(f, keep):
                got = [f(t) for t, p in texts if keep(p)]
                return sum(got) / len(got)

            share = 0.5 if named or r.heading[path] else 0.1
            a, b = ((1 - share) * mean(f, lambda p: p == path) + share * mean(f, lambda p: near is None or near in spelled(r, p)) for f in (len, lambda t: sum(c in ".,;:!?。，、" for c in t)))
            weight[path] = math.sqrt(a * (1 + b))
        total = sum(len(t) for t, _ in texts)
        least = H.THRESHOLD * sum(weight[p] * len(t) for t, p in texts) / max(1, total)
        kept = main_text(page)
        assert kept == "\n".join(t for t, p in texts if weight[p] >= least * (1 - 1e-12))
        with monkeypatch.context() as m:
            m.setattr(H, "path_weights", lambda r, w=H.path_weights: {k: 1.0 for k in w(r)})
            changed += H.main_text(page) != kept
    assert changed > 0.3 * len(pages)


def test_broken_and_deep_pages_take_linear_time():
    def took(page):
        start = time.perf_counter()
        main_text(page)
        return time.perf_counter() - start

    for make in (lambda n: "<div>" * n + "x", lambda n: '<a href="x>' * n, lambda n: "<a " * n, lambda n: "<a " * n + '">', lambda n: "<b>" * n + "<p>t" * n, lambda n: "<div>" * n + "</li>" * n, lambda n: "<ul><li>" + "<div>" * n + "<li>" * n, lambda n: "<script>" * n, lambda n: "<p>" + "</script" * n, lambda n: "<!--" * n, lambda n: "<" * n, lambda n: "<div><dt>" * n):
        small, large = took(make(5_000)), took(make(40_000))
        assert large < 30 * small + 0.5
    assert main_text("<div>" * 50_000 + "<p>" + "Some text, and more. " * 9) == " ".join(["Some text, and more."] * 9)
    assert main_text("<p>1 < 2, and 3 > 2, so it goes.</p>") == "1 < 2, and 3 > 2, so it goes."


def test_extract_whole_pages(spark):
    rows = [(1, "u", PAGE, "t"), (1, "u", PAGE, "t"), (None, None, None, None), (2, "v", "<p>" + "word, " * 200_000 + "</p>", "t")]
    got = extract_text(spark.createDataFrame(rows, "page_id long, url string, html string, text string")).collect()
    assert sorted(r["n_chars"] for r in got) == sorted([len(main_text(PAGE))] * 2 + [0, 1_199_999])
    assert all(r["n_chars"] == len(r["text"]) for r in got)


# -- near duplicates


def brute_components(rows, k=5, percent=75):
    sets = {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        s = {tuple(w[a:a + k]) for a in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
        sets.setdefault(i, []).append(s)
    parent = {i: i for i in sets if i is not None}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    flat = [(i, s) for i, ss in sets.items() if i is not None for s in ss if s]
    for n, (i, a) in enumerate(flat):
        for j, b in flat[:n]:
            if 100 * len(a & b) >= percent * len(a | b):
                x, y = sorted((find(i), find(j)))
                parent[y] = x
    return sets, {i: find(i) for i in parent}


@pytest.mark.parametrize("options", [{}, {"paired": 2, "block": 200, "ordered": 20}])
def test_ngram_join_matches_brute_force(spark, options):
    rng = random.Random(7)
    vocabulary = [f"w{i}" for i in range(400)]
    rows = []
    for g in range(25):
        base = [rng.choice(vocabulary) for _ in range(rng.randint(3, 120))]
        for _ in range(rng.randint(1, 6)):
            w = list(base)
            for _ in range(rng.randint(0, 4)):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
            rows.append((len(rows), " ".join(w if rng.random() < .7 else [x.upper() for x in w])))
    passage = " ".join(vocabulary[:30])
    rows += [(1000 + i, passage + " " + " ".join(rng.choice(vocabulary) for _ in range(rng.randint(0, 12)))) for i in range(40)]
    rows += [(2000, None), (2001, ""), (2002, "one two"), (2003, "ONE\ttwo"), (2004, "one two three")]
    sets, want = brute_components(rows)
    got = {r["doc_id"]: r for r in ngram_components(docs_of(spark, rows), **options).collect()}
    assert {i: r["component_id"] for i, r in got.items()} == want
    assert all(got[i]["n_shingles"] == len(s[0]) for i, s in sets.items())


def doubling(n):
    """Two strings that polynomial hashes modulo a power of two do not tell apart."""
    a, b = "a", "b"
    for _ in range(n):
        a, b = a + b, b + a
    return a, b


def test_ngram_join_tells_doubling_words_apart(spark):
    a, b = doubling(10)
    got = ngram_components(docs_of(spark, [(1, a), (2, b), (3, f"{a} {b}"), (4, f"{b} {a}"), (5, f"x y {a} z q r"), (6, f"x y {b} z q r")])).collect()
    assert all(r["doc_id"] == r["component_id"] for r in got)


def test_ngram_join_large_blocks(spark, monkeypatch):
    import hgpart.llm.ngram_join as J

    monkeypatch.setattr(J, "BLOCK_SETS", 7)
    monkeypatch.setattr(J, "PIVOTS", 2)
    rng = random.Random(12)
    base = [f"w{i}" for i in range(60)]
    rows, chain = [], list(base)
    for i in range(45):  # a chain whose ends differ
        chain[rng.randrange(60)] = f"n{i}"
        rows.append((i, " ".join(chain)))
    for i in range(45, 90):  # boilerplate that is not alike enough
        rows.append((i, " ".join(base[:25] + [f"u{i}_{j}" for j in range(rng.randint(0, 18))])))
    for i in range(90, 130):  # near copies
        w = list(base)
        w[rng.randrange(60)] = f"c{i}"
        rows.append((i, " ".join(w)))
    _, want = brute_components(rows)
    got = {r["doc_id"]: r["component_id"] for r in ngram_components(docs_of(spark, rows), paired=3).collect()}
    assert got == want


def test_ngram_join_edges(spark):
    same = "a b c d e f g h"
    got = ngram_components(docs_of(spark, [(5, same), (5, same), (7, same), (None, same), (9, "x " * 50_000)])).collect()
    assert sorted((r["doc_id"], r["component_id"]) for r in got if r["doc_id"] is not None) == [(5, 5), (5, 5), (7, 5), (9, 9)]
    assert [r["component_id"] for r in got if r["doc_id"] is None] == [None]
    assert ngram_components(docs_of(spark, [])).collect() == []
    h, ends = shingle_sets([b"", b"a b c d e a b c d e a", b"A"])
    assert ends.tolist() == [0, 5, 6] and len(h) == 6


# -- secrets


def test_automaton_against_re():
    rng = random.Random(4)
    rules = [r"a(b|cd)*e?", r"[0-9]{2,4}x", r"x\.y+", r"(foo|fo)[^a-c]", r"\w\d"]
    own = [(compile_rules([(p, False)], False), re.compile(p.encode())) for p in rules]
    every = compile_rules([(p, False) for p in rules], True)
    for _ in range(3000):
        text = bytes(rng.choice(b"abcdefox.y0129 ") for _ in range(rng.randint(0, 14)))
        s, seen = 0, 0
        for b in text:
            s = int(every.next[s, b])
            seen |= int(every.accepts[s])
        for k, (a, r) in enumerate(own):
            s, ok = 0, bool(a.accepts[0])
            for b in text:
                s = int(a.next[s, b])
            ok = bool(a.accepts[s])
            assert ok == bool(r.fullmatch(text)), (rules[k], text)
            assert bool(seen >> k & 1) == any(r.fullmatch(text, i, j) for i in range(len(text)) for j in range(i + 1, len(text) + 1)), (rules[k], text)


BASE_PATTERNS = [re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), re.compile("AKIA[A-Z0-9]+"), re.compile("[0-9a-f]+")]


def base_spans(text):
    out = [(m.start(), 0, m.end()) for m in BASE_PATTERNS[0].finditer(text) if len(m[2]) >= 6]
    out += [(m.start(), 1, m.end()) for m in BASE_PATTERNS[1].finditer(text) if m.end() - m.start() >= 20]
    out += [(m.start(), 2, m.end()) for m in BASE_PATTERNS[2].finditer(text) if m.end() - m.start() >= 24]
    return sorted(out)


def test_secret_spans_match_patterns():
    rng = random.Random(1)
    parts = ["token", "secret", "api_key", "APIKEY", "passwd", "password", "=", ":", " ", "'", '"', "abc", "abcdef12", "é", "AKIA", "ABCDEFGH01234567", "0123456789abcdef", "x", "ſ", "K", "\n", "ghp_"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 30))) for _ in range(4000)]
    scanner = Scanner()
    for text, spans in zip(texts, scanner.scan([t.encode() for t in texts])):
        assert [s for s in spans if scanner.rules[s[1]][0] in BASE] == base_spans(text), text
    text = "é -----BEGIN RSA PRIVATE KEY----- ghp_" + "a1B2" * 9 + " xoxb-123456789012"
    assert [scanner.rules[k][0] for _, k, _ in scanner.scan([text.encode()])[0]] == ["key_block", "forge_token", "chat_token"]


ALL_PATTERNS = [re.compile(p.replace("{12,}", "+") if n == "hex" else p, (re.I if c else 0) | re.A) for n, p, c, _, _ in RULES]


def test_all_spans_match_patterns():
    rng = random.Random(6)
    parts = ["eyJ", "eyJa", ".", "-", "_", "ghp_", "gho_", "ghp", "A1b2" * 9, "xox", "xoxb-", "123456789012345", "-----BEGIN ", "RSA ", "PRIVATE KEY-----", "-----", "é", " ", "token", "=", "AKIA", "x"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 25))) for _ in range(4000)]
    scanner = Scanner()
    for text, spans in zip(texts, scanner.scan([t.encode() for t in texts])):
        want = []
        for k, (p, (_, _, _, least, value)) in enumerate(zip(ALL_PATTERNS, RULES)):
            for m in p.finditer(text):
                if k == 0 and len(re.sub(r"""^[^:=]*[:=]\x20*["']?""", "", m[0])) < value or len(m[0]) < least:
                    continue
                want.append((m.start(), k, m.end()))
        assert spans == sorted(want), text


def test_rules_that_accept_before_they_end():
    rules = (("a", r"ab(cd)*", False, 0, 0), ("b", r"a[a-z]*x|bc", False, 0, 0))
    own, scanner = [re.compile(p) for _, p, _, _, _ in rules], Scanner(rules)
    rng = random.Random(3)
    for _ in range(3000):
        text = "".join(rng.choice("abcdx ") for _ in range(rng.randint(0, 14)))
        assert scanner.scan([text.encode()])[0] == sorted((m.start(), k, m.end()) for k, p in enumerate(own) for m in p.finditer(text)), text


def test_long_runs_are_read_once():
    scanner, took = Scanner(), []
    for n in (20_000, 80_000):
        text = b"eyJ" * n + b" ghp_" * n + b" token=abcdef"
        start = time.perf_counter()
        assert len(scanner.scan([text])[0]) == 1
        took.append(time.perf_counter() - start)
    assert took[1] < 10 * took[0]


def test_scan_secrets_rows(spark):
    rows = [(1, None), (2, ""), (None, "token=abcdef"), (3, "é" * 100_000 + " secret: 'abcdef'"), (3, "token=abc")]
    got = sorted(((r["doc_id"], r["n_assign"], r["spans"]) for r in scan_secrets(docs_of(spark, rows)).collect()), key=str)
    assert got == sorted([(1, 0, ""), (2, 0, ""), (None, 1, "assign:0:12"), (3, 1, "assign:100001:100016"), (3, 0, "")], key=str)
    assert scan_secrets(docs_of(spark, [])).collect() == []


# -- decontamination


def test_decontaminate_matches_brute_force(spark):
    rng = random.Random(9)
    vocabulary = [f"v{i}" for i in range(60)]
    items = [(i, " ".join(rng.choice(vocabulary) for _ in range(rng.choice([3, 9, 10, 14, 25])))) for i in range(12)] + [(50, None), (51, " .,"), (None, "q r s")]
    items.append((60, items[0][1]))
    rows = []
    for i in range(60):
        w = [rng.choice(vocabulary) for _ in range(rng.randint(0, 60))]
        if i % 3 == 0:
            other = (items[rng.randrange(12)][1]).split()
            at = rng.randrange(len(w) + 1)
            w[at:at] = other[rng.randint(0, 2):]
        rows.append((i, ", ".join(x.upper() if rng.random() < .3 else x for x in w)))
    rows += [(100, None), (101, ""), (101, "É q r s é"), (101, "É q r s é"), (None, "v1")]
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
    want = []
    for i, t in rows:
        w, hit, found = words(t), set(), set()
        for item, text in items:
            v = words(text)
            n = min(10, len(v))
            for s in range(len(v) - n + 1 if v else 0):
                for a in range(len(w) - n + 1):
                    if w[a:a + n] == v[s:s + n]:
                        hit |= set(range(a, a + n))
                        if item is not None:
                            found.add(str(item))
        import hashlib

        want.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    bench = spark.createDataFrame([(i, t, 1) for i, t in items], "item_id long, text string, win int")
    got = [tuple(r) for r in decontaminate(docs_of(spark, rows), bench).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    blocks = [tuple(r) for r in decontaminate(docs_of(spark, rows), bench, scan_rows=9).collect()]
    assert sorted(blocks, key=str) == sorted(want, key=str)
    carried = decontaminate(docs_of(spark, rows), bench, carry=("text", "w", "n_hit")).collect()
    assert sorted(((r["doc_id"], r["text"], r["n_hit"]) for r in carried), key=str) == sorted(((i, t, x[2]) for (i, t), x in zip(rows, want)), key=str)
    clean = [(r["doc_id"], r["text"]) for r in drop_contaminated(docs_of(spark, rows), bench).collect()]
    assert sorted(clean, key=str) == sorted(((i, t) for (i, t), x in zip(rows, want) if not x[5]), key=str)
    assert decontaminate(docs_of(spark, []), bench).collect() == []
    clean = decontaminate(docs_of(spark, rows), bench.limit(0)).collect()
    assert len(clean) == len(rows) and not any(r["contaminated"] for r in clean)
