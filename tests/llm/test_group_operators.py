"""Duplicates, n-gram joins, components, shards, packing, neighbours and pages against brute force."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from conftest import NASTY
from hypothesis import given, settings
from hypothesis import strategies as st

from progenrich.llm import ann_block_join, common, crf_extract, extendible_shards, fingerprint_dedup, ngram_join, nnls_packing
from progenrich.llm.common import Generations, Workspace
from progenrich.llm.components import components

WORD = public_tokenizers.path("word_bpe_49k.json")


def union(n, links):
    up = {i: i for i in n}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {i: find(i) for i in n}


def test_components(spark):
    rng = random.Random(4)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(180)] + [(i, i + 1) for i in range(400, 460)] + [(500, i) for i in range(501, 540)] + [(7, 7)]
    df = spark.createDataFrame(links, "a long, b long")
    got = {r["node"]: r["component"] for r in components(df, Workspace(spark, "t")).collect()}
    want = union({x for ab in links for x in ab}, links)
    nodes = {x for a, b in links if a != b for x in (a, b)}
    assert got == {x: want[x] for x in nodes}
    assert components(df.limit(0), Workspace(spark, "t")).count() == 0


# --- exact duplicates -----------------------------------------------------------------------------


def brute_dedup(rows):
    groups = collections.defaultdict(list)
    for i, t in rows:
        groups[re.sub("[\x20\x09-\x0d]", "", t or "")].append((-len(t or ""), i))
    out = {}
    for body, members in groups.items():
        keep = min(members)[1]
        for _, i in members:
            out[i] = (keep, len(members), i == keep, hashlib.sha256(body.encode()).hexdigest())
    return out


def copies(seed, n=150):
    rng = random.Random(seed)
    base = ["alpha beta gamma", "alphabeta gamma", "x y z", "one two three four", "é漢 字"] + NASTY
    return [(i, rng.choice(["{}", " {}", "{}\n", "{}"]).format(t) if (t := rng.choice(base)) is not None else None) for i in range(n)]


@pytest.mark.parametrize("primes, bases", [(fingerprint_dedup.PRIMES, fingerprint_dedup.BASES), ((3,), (2,))])
def test_dedup(spark, docs, primes, bases):
    """With the tiny prime nearly all texts collide, and the comparison alone tells them apart."""
    rows = copies(1)
    got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for r in fingerprint_dedup.duplicate_classes(spark, docs(rows), primes=primes, bases=bases, chunk=7).collect()}
    assert got == brute_dedup(rows)


def test_dedup_edges(spark, docs):
    assert fingerprint_dedup.duplicate_classes(spark, docs([])).count() == 0
    assert [(r["keep_id"], r["group_size"]) for r in fingerprint_dedup.duplicate_classes(spark, docs([(5, "a")])).collect()] == [(5, 1)]
    assert [r["kept"] for r in fingerprint_dedup.duplicate_classes(spark, docs([(5, "a"), (5, "a")])).collect()] == [True, True]
    out = fingerprint_dedup.duplicate_classes(spark, docs([(None, "a   b"), (None, "ab"), (2, "a b"), (3, "ab")])).collect()
    assert sorted((r["doc_id"] or 0, r["keep_id"] or 0, r["group_size"], r["kept"]) for r in out) == [(0, 0, 1, True), (0, 0, 1, True), (2, 2, 2, True), (3, 2, 2, False)]


@given(st.binary(max_size=300), st.integers(0, 300))
@settings(max_examples=200, deadline=None)
def test_fingerprints_compose(data, cut):
    a, b = data[:cut], data[cut:]
    f = fingerprint_dedup
    assert f.combine(f.fingerprint(a), f.fingerprint(b), len(b)) == f.fingerprint(data) == f.fingerprint(data, size=5)


# --- n-gram join ----------------------------------------------------------------------------------


def grams(t, n):
    words = re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    if not words:
        return frozenset()
    return frozenset(tuple(words[i : i + n]) for i in range(max(1, len(words) - n + 1)))


def brute_join(rows, n, percent):
    sets = {i: grams(t, n) for i, t in rows}
    ids = sorted(sets)
    links = []
    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            k = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * k >= percent * (len(sets[a]) + len(sets[b]) - k):
                links.append((a, b))
    return {i: (len(sets[i]), c) for i, c in union(ids, links).items()}


def family(seed, groups=12, size=10):
    """Near copies around the threshold, chains, exact copies in other case, and unrelated texts."""
    rng = random.Random(seed)
    vocab = [f"w{k}" for k in range(400)]
    rows = []
    for _ in range(groups):
        base = [rng.choice(vocab) for _ in range(rng.choice([3, 5, 12, 40, 120]))]
        for _ in range(size):
            w = list(base)
            for _ in range(rng.choice([0, 0, 1, 1, 2, 3, 5])):
                w[rng.randrange(len(w))] = rng.choice(vocab)
            if rng.random() < 0.3:
                base = w
            rows.append(" ".join(w).upper() if rng.random() < 0.2 else " ".join(w))
    return list(enumerate(rows + NASTY))


@pytest.mark.parametrize("seed, n, percent, rounds", [(1, 4, 85, 2), (2, 5, 80, 2), (3, 4, 85, 0), (4, 2, 60, 1)])
def test_ngram_join(spark, docs, seed, n, percent, rounds):
    rows = family(seed)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicate_components(spark, docs(rows).repartition(5), n, percent, rounds).collect()}
    assert got == brute_join(rows, n, percent)


@pytest.mark.parametrize("cells", [1, 64])
def test_ngram_join_with_a_full_sieve(spark, docs, cells, monkeypatch):
    """A sieve that lets (nearly) everything through changes no row."""
    monkeypatch.setattr(common, "SIEVE_CELLS", cells)
    rows = family(6, 4, 6)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicate_components(spark, docs(rows), 4, 85).collect()}
    assert got == brute_join(rows, 4, 85)


@pytest.mark.parametrize("rounds", [0, 1])
def test_hot_ngrams_are_dealt(spark, docs, rounds, monkeypatch):
    """Every n-gram counts as hot: its rows go to many parts, and no link is lost."""
    monkeypatch.setattr(ngram_join, "HOT_ROWS", 1)
    monkeypatch.setattr(ngram_join, "HOT_SHARE", 0)
    rows = family(8, 4, 8)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicate_components(spark, docs(rows).repartition(3), 4, 85, rounds).collect()}
    assert got == brute_join(rows, 4, 85)


def test_sieve_never_loses_an_id(spark, monkeypatch):
    rows, ids = spark.range(0, 5000).selectExpr("id AS doc_id", "1 AS hit", "2 AS cell"), spark.range(0, 5000, 7).selectExpr("id AS doc_id")
    for cells in (1, 16, 1 << 18):
        monkeypatch.setattr(common, "SIEVE_CELLS", cells)
        assert {r[0] for r in common.kept_of(rows, ids).select("doc_id").collect()} == set(range(0, 5000, 7))
        assert common.without(rows, ids).columns == rows.columns
        assert {r[0] for r in common.without(rows, ids).select("doc_id").collect()} == set(range(5000)) - set(range(0, 5000, 7))
    assert common.without(rows, ids.limit(0)).count() == 5000 and common.kept_of(rows, ids.limit(0)).count() == 0


def test_long_words_are_not_stored():
    made = Generations(len, 10)
    assert made["x" * 65] == 65 and made["ab"] == 2 and made.all(["y" * 100, "c"]) == [100, 1] and set(made) == {"ab", "c"}


@pytest.mark.parametrize("seed, n, percent", [(1, 4, 85), (4, 2, 60)])
def test_links_are_all_counted(spark, docs, seed, n, percent):
    """Pairs within one component count too: a group of near copies links each with each."""
    words = " ".join(f"w{i}" for i in range(200))
    rows = [(i, f"{words} tail{i}") for i in range(6)] + [(20, f"{words} tail0")]
    rng = random.Random(seed)
    rows += [(100 + i, " ".join(rng.choices("abc", k=rng.randrange(1, 9)))) for i in range(60)]
    sets = {}
    for i, t in rows:
        ws = t.split()
        sets[i] = frozenset(tuple(ws[j : j + n]) for j in range(max(1, len(ws) - n + 1)))
    each = set(sets.values())
    want = {i: sum(a != b and 100 * len(a & b) >= percent * len(a | b) for b in each) for i, a in sets.items()}
    out = ngram_join.near_duplicate_links(spark, docs(rows).repartition(3), n, percent).collect()
    assert {r["doc_id"]: r["links"] for r in out} == want and [want[i] for i in (0, 3, 20)] == [5, 5, 5]
    plain = ngram_join.near_duplicate_components(spark, docs(rows), n, percent)
    assert plain.columns == ["doc_id", "n_shingles", "component_id"]
    assert {r["doc_id"]: r["component_id"] for r in out} == {r["doc_id"]: r["component_id"] for r in plain.collect()}


def test_ngram_join_edges(spark, docs):
    assert ngram_join.near_duplicate_components(spark, docs([])).count() == 0
    out = ngram_join.near_duplicate_components(spark, docs([(3, "a b"), (3, "a b"), (None, "a b"), (4, None), (5, "")])).collect()
    assert sorted(((r["doc_id"], r["component_id"], r["n_shingles"]) for r in out), key=str) == [(3, 3, 1), (3, 3, 1), (4, 4, 0), (5, 5, 0), (None, None, 1)]


def test_generations_keep_what_is_used():
    made = []
    g = Generations(lambda k: made.append(k) or k * 2, 3)
    for k in [1, 2, 3, 1, 4, 1, 5, 1, 6, 1, 7, 1]:
        assert g[k] == k * 2
    assert made.count(1) == 1


# --- shards ---------------------------------------------------------------------------------------


@pytest.mark.parametrize("limit", [1, 60, 500, 10**6])
def test_shards(spark, docs, limit):
    rows = [(i, "t" * (i % 50)) for i in range(300)] + [(7, "same")] * 20 + [(None, None), (900, "b" * 3000)]
    out = extendible_shards.shards(spark, docs(rows), limit).collect()
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["n_bytes"]) for r in out) == sorted((-1 if i is None else i, len(t or "")) for i, t in rows)
    sizes = collections.defaultdict(list)
    for r in out:
        sizes[r["shard_prefix"], r["shard_depth"], r["page"]].append(r["n_bytes"])
    assert all(sum(v) <= limit or sum(x > 0 for x in v) == 1 for v in sizes.values())
    leaves = {(p, d) for p, d, _ in sizes}
    for p, d in leaves:  # no leaf lies below another
        assert not any((p >> (d - e), e) in leaves for e in range(d))
    if limit == 10**6:
        assert leaves == {(0, 0)}


def test_shards_edges(spark, docs):
    assert extendible_shards.shards(spark, docs([]), 10).count() == 0


# --- packing --------------------------------------------------------------------------------------


@given(st.lists(st.integers(1, 64), max_size=200))
@settings(max_examples=100, deadline=None)
def test_plans_hold_every_piece_once(lengths):
    hist = np.bincount(lengths, minlength=65) if lengths else np.zeros(65, int)
    plan = nnls_packing.make_plan(hist, 64)
    got = collections.Counter()
    for n, ls in plan.groups:
        assert sum(ls) <= 64 and n > 0
        for x in ls:
            got[x] += n
    assert got == collections.Counter(lengths)


def test_nnls_finds_an_exact_mixture():
    rng = np.random.default_rng(1)
    a = rng.random((8, 20))
    x = np.zeros(20)
    x[[2, 7, 11]] = [3.0, 1.5, 4.0]
    got = nnls_packing.nnls(a, a @ x)
    assert (got >= 0).all() and np.allclose(a @ got, a @ x, atol=1e-6)


def test_combinations_fill_the_window():
    ways = nnls_packing.combinations(12, 2)
    assert len(ways) == len(set(ways)) and all(sum(k * m for k, m in w) == 12 and min(k for k, _ in w) >= 2 and len(w) <= 3 for w in ways)
    assert ((3, 4),) in ways and ((12, 1),) in ways and ((4, 1), (2, 4)) in ways and ((5, 1), (4, 1), (3, 1)) in ways


def test_least_squares_places_most_of_the_mass():
    rng = np.random.default_rng(2)
    hist = np.bincount(np.clip(rng.lognormal(6.2, 0.9, 200_000).astype(int), 1, 4095), minlength=4097)
    left = hist.astype(np.int64).copy()
    free = nnls_packing.solve(left, 4096)
    took = np.zeros(4097, np.int64)
    for space, groups in free.items():
        for n, lengths in groups:
            assert sum(lengths) + space == 4096 and space >= 0
            np.add.at(took, list(lengths), n)
    assert (took + left == hist).all() and (left * np.arange(4097)).sum() < 0.2 * (hist * np.arange(4097)).sum()


def test_padding_is_small():
    rng = np.random.default_rng(2)
    hist = np.bincount(np.clip(rng.lognormal(6.2, 0.9, 20_000).astype(int), 1, 4096), minlength=4097)
    plan = nnls_packing.make_plan(hist, 4096)
    assert 1 - hist.dot(np.arange(4097)) / (4096 * plan.sequences) < 0.01


@pytest.mark.parametrize("window", [16, 100])
def test_packing(spark, docs, window):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(WORD)
    texts = NASTY + ["The Cat, sat. ON the mat's mat!!!", "Σίσυφος ΣΑΣ İ& ǅ", "a1b2 c3"] + [f"word{i} " * (i % 9) for i in range(60)]
    rows = list(enumerate(texts))
    out = nnls_packing.pack(spark, docs(rows), WORD, window=window, end_id=2).collect()
    ids = {i: tok.encode(t or "", add_special_tokens=False).ids + [2] for i, t in rows}
    per = collections.defaultdict(list)
    for r in out:
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] and r["ids_crc32"] == zlib.crc32(b"".join(x.to_bytes(4, "little") for x in part)) and r["doc_tokens"] == len(ids[r["doc_id"]])
        per[r["doc_id"]].append((r["start"], r["length"]))
    for i, v in ids.items():
        at = 0
        for start, size in sorted(per[i]):
            assert start == at
            at += size
        assert at == len(v)
    seqs = collections.defaultdict(list)
    for r in out:
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
    assert sorted(seqs) == list(range(len(seqs)))
    for v in seqs.values():
        at = 0
        for offset, size in sorted(v):
            assert offset == at
            at += size
        assert at <= window
    assert nnls_packing.pack(spark, docs([]), WORD).count() == 0


# --- neighbours -----------------------------------------------------------------------------------


def brute_nearest(rows, queries, k):
    fine = [(i, np.array(v, float)) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    out = {}
    for q, x in fine:
        if q in queries:
            d = sorted((float(np.sqrt(sum((a - b) ** 2 for a, b in zip(x, y)))), i) for i, y in fine if i != q and len(y) == len(x))
            out[q] = [i for _, i in d[:k]]
    return out


@pytest.mark.parametrize("dim, tile", [(3, 7), (16, 2048)])
def test_nearest(spark, dim, tile, monkeypatch):
    monkeypatch.setattr(ann_block_join, "TILE", tile)
    monkeypatch.setattr(ann_block_join, "CELL_QUERIES", 9)
    rng = np.random.default_rng(3)
    rows = [(i, [float(x) for x in np.round(rng.normal(size=dim), 1)]) for i in range(120)]
    rows += [(200 + i, rows[0][1]) for i in range(30)] + [(300, None), (310, [0.0] * dim), (320, [float("nan")] * dim), (330, [None] + [1.0] * (dim - 1)), (340, [1.0, 2.0]), (350, []), (None, rows[0][1]), (360, [1e30] * dim), (370, [1e-30] * dim)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").selectExpr("*", "1 AS rank", "2 AS score", "3 AS query_id", "4 AS g", "5 AS dim").repartition(4)
    got = collections.defaultdict(list)
    for r in sorted(ann_block_join.nearest(spark, df, df.where("vec_id % 10 = 0"), 10).collect(), key=lambda r: (r["query_id"], r["rank"])):
        got[r["query_id"]].append(r["vec_id"])
    want = brute_nearest(rows, {i for i, _ in rows if i is not None and i % 10 == 0}, 10)
    assert dict(got) == {q: v for q, v in want.items() if v}
    assert ann_block_join.nearest(spark, df.limit(0), df.limit(0)).count() == 0


def test_repeated_rows_leave_k_neighbours(spark):
    """Every row twice, and some ids with a second, nearer vector: still the k nearest distinct ids."""
    rng = np.random.default_rng(5)
    rows = [(i, [float(x) for x in rng.normal(size=4)]) for i in range(60)] * 2
    rows += [(i, [x + 0.01 for x in rows[0][1]]) for i in range(40, 43)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").coalesce(1)
    got = [r["vec_id"] for r in sorted(ann_block_join.nearest(spark, df, df.where("vec_id = 0").limit(1), 10).collect(), key=lambda r: r["rank"])]
    best = {}
    for i, v in rows:
        if i:
            best[i] = min(best.get(i, 1e9), float(np.linalg.norm(np.array(v) - np.array(rows[0][1]))))
    assert got == sorted(best, key=lambda i: (round(best[i], 12), i))[:10]


def test_quantised_bounds_hold():
    rng = np.random.default_rng(4)
    x, y = rng.normal(size=(20, 32)), rng.normal(size=(300, 32))
    block = ann_block_join.QueryBlock(np.arange(20) + 1000, x)
    limit = np.full(20, np.inf)
    qi, ci = ann_block_join.search_tile(block, ann_block_join.QueryBlock(np.arange(300), y), 5, limit)
    d = ((x[:, None] - y) ** 2).sum(2)
    assert (np.sort(d, axis=1)[:, 4] <= limit + 1e-9).all()
    kept = set(zip(qi.tolist(), ci.tolist()))
    assert all((q, c) in kept for q in range(20) for c in np.argsort(d[q])[:5]) and len(kept) < 6000 / 4


# --- pages ----------------------------------------------------------------------------------------


def test_crf_on_unseen_layouts():
    field = crf_extract.trained()
    right = total = 0
    for p in crf_extract.training_pages(120, seed=77):
        found = crf_extract.blocks(p)
        plain = [crf_extract.Block(b.text.replace(crf_extract.MARK, ""), b.path, b.links) for b in found]
        for b, keep in zip(found, field.decode(plain)):
            right += keep == (crf_extract.MARK in b.text)
            total += 1
    assert right / total > 0.97


def test_viterbi_is_the_best_path():
    import itertools

    f = crf_extract.trained()
    found = crf_extract.blocks("<nav><a href=x>a</a></nav><article><h1>T</h1><p>One two three.</p></article><footer>&copy; x</footer>")
    e = [f.emission(b) for b in found]

    def value(labels):
        s = f.start[labels[0]] + e[0] * labels[0]
        for i in range(1, len(labels)):
            s += f.step[labels[i - 1]][labels[i]] + e[i] * labels[i]
        return s

    best = max(itertools.product((0, 1), repeat=len(e)), key=value)
    assert [bool(x) for x in best] == f.decode(found)


def test_pages(spark):
    page = '<html><head><title>t</title><style>p{}</style><script>var t="</p>";</script></head><body><nav><ul><li><a href="/a">home</a></li></ul></nav><!-- ad --><div class="ad">buy now</div><article><h1>Title &amp; more</h1><p><b>First   line<br>goes on.<p>Second &quot;line&quot; is here.</article><footer>&copy; site</footer>'
    rows = [(1, "u", page), (2, "u", None), (3, None, ""), (4, "u", "<"), (5, "u", "<p"), (None, "u", "plain text"), (6, "u", "<div>" * 3000 + "x"), (1, "u", page)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'zz' AS text", "9 AS n_chars")
    out = crf_extract.extract(df).collect()
    assert len(out) == len(rows)
    got = {r["page_id"]: r for r in out}
    assert got[1]["text"] == 'Title & more First line goes on. Second "line" is here.' and got[1]["n_chars"] == len(got[1]["text"])
    assert all(got[i]["text"] == "" for i in (2, 3, 4, 5))
    assert crf_extract.extract(df.limit(0)).count() == 0


def test_pages_table_by_brute_force(spark):
    """The pages of the tables hold one article each: its blocks, read by plain patterns, are the main text."""
    import html

    def plain(page):
        parts = re.split(r"</?(?:h1|p|article)[^>]*>", re.search(r"<article>(.*?)</article>", page, re.S)[1])
        parts = [" ".join(html.unescape(re.sub(r"<[^>]*>", "", x.replace("<br>", " "))).split()) for x in parts]
        return " ".join(x for x in parts if x)

    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    want = {r["page_id"]: plain(r["html"]) for r in pages.collect()}
    got = crf_extract.extract(pages).collect()
    assert len(got) == len(want) and {r["page_id"]: r["text"] for r in got} == want


def test_text_inside_inline_elements_stays():
    page = "<nav><a href=x>Home</a></nav><article><h1>Title here</h1><p>Let <math><mi>x</mi></math> and <svg><text>y</text></svg> <object>hold</object>.</p><p>More text of the article, in whole sentences. And some more.</p></article><footer>&copy; 2020</footer>"
    assert crf_extract.main_text(page, crf_extract.trained()) == "Title here Let x and y hold. More text of the article, in whole sentences. And some more."


BROKEN = ["<a x " * 60_000, "<div class='a b'>x" * 40_000, '<a "' * 60_000 + ">", "<title>" * 60_000, "<head>" * 60_000, "<!-- " * 60_000, "<" * 200_000, "<ul><li>" + "<h1>x" * 20_000 + "<li></li>" * 20_000, "<div>" * 500 + "</p>" * 60_000, "&#" * 100_000]


@pytest.mark.parametrize("page", BROKEN, ids=[p[:8] for p in BROKEN])
def test_broken_markup_is_read_in_linear_time(page):
    import time

    field, began = crf_extract.trained(), time.time()
    crf_extract.main_text(page, field)
    assert time.time() - began < 8


def test_deep_elements_close_in_order():
    deep = "<div>" * 2000 + "inner" + "</div>" * 2000 + "<p>after"
    found = crf_extract.blocks(deep)
    assert [b.text for b in found] == ["inner", "after"] and found[1].path.up is None
