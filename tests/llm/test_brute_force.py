"""Operators against slow and plain versions of themselves."""

from __future__ import annotations

import html
import itertools
import math
import random
import re
from collections import Counter

import numpy as np
import pytest

from chronofold.llm import encoding, language, maxent, mixing, nearcopies, pagetext

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet").cache()


def shingles(text):
    words = (text or "").encode().lower().split()
    return {b" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))}


def groups(texts: dict[int, str]) -> dict[int, int]:
    """Smallest id reachable over pairs of similarity 0.8 or more, by all pairs that share a shingle."""
    sets = {i: shingles(t) for i, t in texts.items()}
    holders: dict[bytes, list[int]] = {}
    for i in sorted(sets):
        for s in sets[i]:
            holders.setdefault(s, []).append(i)
    common: Counter = Counter()
    for own in holders.values():
        common.update(itertools.combinations(own, 2))
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for (a, b), n in common.items():
        if 5 * n >= 4 * (len(sets[a]) + len(sets[b]) - n):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    return {i: find(i) for i in sets}


def test_near_copies_are_those_of_all_pairs(spark, docs):
    rng = random.Random(5)
    texts = {r.doc_id: r.text for r in docs.collect()}
    words = [f"w{i}" for i in range(400)]
    for _ in range(150):  # short texts, each with a copy of one more or another word
        base = [rng.choice(words) for _ in range(rng.randint(6, 20))]
        for own in (base, [*base, rng.choice(words)], base[:-1] + [rng.choice(words)]):
            texts[len(texts) + 10_000] = " ".join(own)
    hub = [rng.choice(words) for _ in range(200)]
    for _ in range(300):  # like the first, not like one another
        own = list(hub)
        for at in rng.sample(range(0, 200, 5), 3):
            own[at] = rng.choice(words)
        texts[len(texts) + 10_000] = " ".join(own)
    want = groups(texts)
    rows = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    found = {r.doc_id: r.root for r in nearcopies.near_copy_roots(rows).collect()}
    assert {i: found.get(i, i) for i in texts} == want and len(set(want.values())) < len(texts) - 500


def test_forest_connects_what_all_edges_do():
    rng = np.random.default_rng(3)
    for n in (1, 5, 40, 300):
        a, b = rng.integers(0, n + 2, (2, n))
        kept = nearcopies.forest(a, b)

        def parts(x, y):
            label = np.arange(n + 2)
            while True:
                new = label.copy()
                np.minimum.at(new, x, label[y])
                np.minimum.at(new, y, label[x])
                if (new == label).all():
                    return label.tolist()
                label = new

        assert parts(a, b) == parts(a[kept], b[kept])


def test_encoder_on_odd_texts():
    rng = random.Random(1)
    alphabet = ["a", "b", " ", "  ", "\n", "'", "s", "1", ".", "é", "日", "\t", "<|endoftext|>", "\x1c", "A", "ñ", "x" * 50]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 14))) for _ in range(3000)] + [None, ""]
    own = encoding.ChunkEncoder(memo_chunks=500)
    for x, ids in zip(texts, own.encode(texts), strict=True):
        assert np.frombuffer(ids, dtype="<u4").tolist() == own._library.encode(x or "", add_special_tokens=False).ids


def test_language_scores_by_words_and_backoff():
    rows = {"xx": "abcd abce abcd zz", "yy": "abcd bcde qqqq"}
    counts: dict[tuple, int] = Counter()
    for name, text in rows.items():
        for w in text.split():
            counts[name, 0, w] += 1
            for n in range(1, 6):
                counts.update((name, n, g) for g in language.grams_of(w, n))
    names = sorted(rows)

    def key(n, g):
        if n == 0:
            return language.key_of(g)
        word = g.strip("␂␃")
        keys, _ = language.gram_keys([word], n)
        grams = language.grams_of(word, n)
        return int(keys[grams.index(g)])

    # n-grams with a mark are looked up inside of their own word, where they have the same code points
    entries = []
    for (name, n, g), c in counts.items():
        inside = [w for w in " ".join(rows.values()).split() if n and g in language.grams_of(w, n)]
        k = language.key_of(g) if not n else int(language.gram_keys([inside[0]], n)[0][language.grams_of(inside[0], n).index(g)])
        entries.append((names.index(name), n, k, c))
    at, lengths, keys, seen = (np.array(x) for x in zip(*[(a, n, np.uint64(k), c) for a, n, k, c in entries]))
    model = language.LanguageModel(at, names, lengths, keys.astype(np.uint64), seen)

    def slow(word):
        for n in (0, 5, 4, 3, 2, 1):
            grams = [word] if n == 0 else language.grams_of(word, n)
            known = [g for g in grams if any((x, n, g) in counts for x in names)]
            if known:
                size = len({g for _, m, g in counts if m == n})
                total = {x: sum(c for (y, m, _), c in counts.items() if (y, m) == (x, n)) for x in names}
                return [np.mean([math.log(counts.get((x, n, g), 0) + language.SMOOTHING) - math.log(total[x] + language.SMOOTHING * size) for g in known]) for x in names]
        return [0.0] * len(names)

    words = ["abcd", "zz", "abcf", "xbcd", "q", "unknown", "ééé", "abc"]
    assert np.allclose(model._scores(words), [slow(w) for w in words], atol=1e-5)


def test_maxent_is_a_distribution_and_scores_add_up(spark):
    rng = random.Random(2)
    texts = [" ".join(rng.choice("a b c d e f g".split()) for _ in range(rng.randint(0, 30))) + f" rare{i % 40}" for i in range(200)]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    training = rows.where("doc_id < 150")
    model = maxent.train(training)
    seen = Counter(w for t in texts[:150] for w in maxent.words_of(t))
    outside = [w for w in seen if w not in model.words[: model.model]]
    history = maxent.words_of(texts[0])[:5]
    tails = model.outside + len(outside) + 1

    def prob(word):  # of a word (None: the end, "": never seen) after the history
        ids = np.array([{w: i + 2 for i, w in enumerate(model.words[: model.model])}.get(w, 1) for w in history] + [0])
        own = 0 if word is None else {w: i + 2 for i, w in enumerate(model.words[: model.model])}.get(word, 1)
        features = maxent._features(ids, np.array([len(ids) - 1]), model.bits)
        chosen = np.full(len(ids), model.classes[own])
        p = math.exp(maxent.class_logs(model.weights, features, chosen)[-1])
        if own == 1:
            return p * (seen.get(word, 0) + 1) / tails
        return p * math.exp(model.within[own])

    assert abs(sum(map(prob, [*seen, None, b""])) - 1) < 1e-5
    found = {r.doc_id: r for r in maxent.score(rows, rows.doc_id < 150).collect()}
    for d in (0, 160):
        total = 0.0
        for n, w in enumerate([*maxent.words_of(texts[d]), None]):
            history = maxent.words_of(texts[d])[:n]
            total += math.log10(prob(w))
        assert abs(found[d].score - total) < 1e-3


def test_mixing_is_the_direct_solution(spark):
    rng = np.random.default_rng(4)
    p = rng.dirichlet([0.3, 0.4, 0.2], 400)
    n = rng.integers(1, 500, 400)
    rows = spark.createDataFrame([(i, int(k), x.tolist()) for i, (k, x) in enumerate(zip(n, p))], "doc_id long, n_tokens long, p array<double>")
    for weights, most in (({"good": 0.8, "plain": 0.2}, None), (None, 1.0), ({"good": 0.2, "plain": 0.8}, 2.0)):
        m = mixing.solve(rows, weights, most=most)
        total, share = n.sum(), (n @ p) / n.sum()
        top, r = math.inf if most is None else most, np.ones(len(n))
        for _ in range(60_000):  # plain steps
            r = np.clip(r - (p @ (((r * n) @ p - m.target) / total / share) + m.ridge * (r - 1)) / (3 + m.ridge), 0, top)
        assert np.abs(m.rates(p) - r).max() < 2e-3 and m.gradient < mixing.TOLERANCE
        if most is None:
            assert np.abs(m.totals[:2] / m.target[:2] - 1).max() < 0.01


def test_repeated_labels_count_once(spark, docs):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    once = mixing.train(docs, labels)
    again = mixing.train(docs, labels.unionByName(labels))
    assert once.index == again.index and np.allclose(once.weights, again.weights)


def _article(page):
    inner = re.search(r"<article>(.*?)(</article>|$)", page, re.S)[1]
    blocks = [" ".join(html.unescape(re.sub(r"<[^>]*>?", " ", b)).split()) for b in re.split(r"</?p>|</?h\d>", inner)]
    return "\n".join(filter(None, blocks))


@pytest.mark.parametrize("classless", [False, True])
def test_the_tree_alone_finds_articles(spark, classless):
    """Without the word lists and the rules of markup, also on pages of plain div elements."""
    own = {r.page_id: r for r in spark.read.parquet(f"{SF}/pages.parquet").collect()}

    def plain(page):
        page = re.sub(r' (class|id)="[^"]*"', "", page)
        return re.sub(r"<(/?)(nav|article|footer|header|aside)\b[^>]*>", r"<\1div>", page)

    rows = [(i, r.url, plain(r.html) if classless else r.html) for i, r in own.items()]
    found = {r.page_id: r.text for r in pagetext.extract(spark.createDataFrame(rows, "page_id long, url string, html string"), markup=False).collect()}
    whole = {i: pagetext.main_text(h, markup=False) for i, _, h in rows}
    assert sum(found[i] != whole[i] for i in own) >= 0.95 * len(own)
    assert sum(found[i] == _article(own[i].html) for i in own) >= 0.9 * len(own)


def test_paths_joined_by_host_give_the_same(spark, monkeypatch):
    pages = spark.read.parquet(f"{SF}/pages.parquet").withColumn("host", pages_null()).limit(60)
    want = sorted((r.page_id, r.text) for r in pagetext.extract(pages).collect())
    monkeypatch.setattr(pagetext, "MAX_BROADCAST", -1)
    assert sorted((r.page_id, r.text) for r in pagetext.extract(pages).collect()) == want


def pages_null():
    from pyspark.sql import functions as F

    return F.lit(None).cast("string")
