"""Text operators against brute force, and on null, empty, repeated, hot and missing rows."""

from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from gnn_delta.llm import bpe, classifiers, components, debruijn, decontaminate, exact_dedup, langid, queries, simhash, suffix, suffix_dedup, urls
from gnn_delta.llm.common import fold

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, keep_id long, rep long"
WORDS = "the of and ing tion er on re th an ha ou".split()


def text(rng: random.Random, n: int) -> str:
    return " ".join("".join(rng.choice(WORDS) for _ in range(rng.randint(1, 3))) for _ in range(n))


@pytest.fixture(scope="module")
def corpus() -> list[tuple]:
    rng = random.Random(4)
    base = text(rng, 90)
    passage = text(rng, 40)
    texts: list[str | None] = [None, "", " \n\t", "A", "a", "Één ñ 日本 <|endoftext|>", base, base, base.upper(), base + " tail", passage]
    texts += [text(rng, 15) + " " + passage + "\n" + text(rng, 15) for _ in range(12)]
    texts += ["ha " * 300, "x" * 700, "ab" * 400, text(rng, 6000)]
    words = base.split()
    for i in range(10):
        w = list(words)
        w[5 * i] = "changed"
        texts.append(" ".join(w))
    texts += [base] * 20  # a hot group
    return [(i, t, "en" if i % 3 else None, "src0", 0, -1, 7) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def docs(spark, corpus):
    return spark.createDataFrame(corpus, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def lower(t: str) -> str:
    return re.sub("[A-Z]", lambda m: m[0].lower(), t)


def words_of(t: str | None) -> list[str]:
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def test_word_spans(docs, corpus):
    got = {r.doc_id: r for r in debruijn.dedup(docs, with_text=True).collect()}
    seen: set[tuple] = set()
    for i, t, *_ in corpus:
        w = words_of(t)
        gone = [False] * len(w)
        for j in range(len(w) - 19):
            k = tuple(w[j : j + 20])
            if k in seen:
                gone[j : j + 20] = [True] * 20
            seen.add(k)
        kept = " ".join(a for a, g in zip(w, gone, strict=True) if not g)
        assert (got[i].n_words, got[i].n_removed, got[i].kept) == (len(w), sum(gone), kept), i
        assert got[i].kept_sha256 == hashlib.sha256(kept.encode()).hexdigest()


def test_word_spans_of_hot_buckets(docs):
    """Every bucket beyond the limit: edges are dealt anew one by one, with the same result."""
    key = lambda r: (r.doc_id, r.n_words, r.n_removed, r.n_spans, r.kept_sha256)
    assert sorted(map(key, debruijn.dedup(docs, held=1).collect())) == sorted(map(key, debruijn.dedup(docs).collect()))


def test_byte_spans(docs, corpus):
    got = {r.doc_id: r for r in suffix_dedup.dedup(docs, with_text=True).collect()}
    seen: set[bytes] = set()
    for i, t, *_ in corpus:
        raw = (t or "").encode()
        gone = bytearray(len(raw))
        for j in range(len(raw) - 99):
            k = raw[j : j + 100]
            if k in seen:
                gone[j : j + 100] = b"\1" * 100
            seen.add(k)
        kept = bytes(a for a, g in zip(raw, gone, strict=True) if not g)
        assert (got[i].n_bytes, got[i].n_removed, bytes(got[i].kept), got[i].n_spans) == (len(raw), sum(gone), kept, len(re.findall(b"\1+", bytes(gone)))), i


@pytest.mark.parametrize("limits", [{"held": 1}, {"group": 1}])
def test_byte_spans_of_hot_anchors(docs, limits):
    """Every bucket, or every anchor's group of contexts, beyond the limit: dealt anew by name, with the same result."""
    key = lambda r: (r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256)
    assert sorted(map(key, suffix_dedup.dedup(docs, **limits).collect())) == sorted(map(key, suffix_dedup.dedup(docs).collect()))


def test_spans_of_a_shared_document_with_tied_rows(spark):
    """Two sources for the same windows must stay two paths."""
    from gnn_delta.llm.repeats import compacted

    rows = [(5, 0, 10, 1, 0), (5, 0, 10, 2, 7), (5, 10, 5, 1, 10), (5, 40, 2, 1, 40)]
    got = compacted(spark.createDataFrame(rows, "doc long, start long, n long, src_doc long, src_start long")).first().spans
    assert all((s.src_doc, s.src_start - s.start) in {(1, 0), (2, 7)} for s in got)
    assert sum(s.n for s in got) >= 27


@pytest.mark.parametrize("limit", [40, 1 << 20])
def test_suffix_array(limit):
    rng = random.Random(limit)
    for _ in range(300):
        t = [rng.randrange(1, 1 + rng.choice([1, 2, 4])) for _ in range(rng.randrange(0, 40))] + [0]
        cap = rng.choice([1, 3, 100])
        order, common = suffix.suffix_array(np.array(t), cap, limit)
        want = sorted(range(len(t)), key=lambda i: t[i:])
        assert sorted(order.tolist()) == list(range(len(t)))
        assert [t[i : i + cap] for i in order] == [t[i : i + cap] for i in want]
        for k in range(1, len(t)):
            a, b, n = t[order[k - 1] :], t[order[k] :], 0
            while n < min(cap, len(a), len(b)) and a[n] == b[n]:
                n += 1
            assert common[k] == n


def test_exact_dedup(docs, corpus):
    for keep, best in (("largest", max), ("smallest", min)):
        got = {r.doc_id: r for r in exact_dedup.mark(docs, keep=keep).collect()}
        groups: dict[str, list[int]] = {}
        for i, t, *_ in corpus:
            groups.setdefault(lower(t or ""), []).append(i)
        assert len(got) == len(corpus)
        for t, ids in groups.items():
            for i in ids:
                r = got[i]
                assert (r.keep_id, r.group_size, r.kept) == (best(ids), len(ids), i == best(ids))
                assert r.text_sha256 == hashlib.sha256(t.encode()).hexdigest()
    assert exact_dedup.dedup(docs).count() == len(groups)
    assert {r.doc_id: r.keep_id for r in exact_dedup._mark_by_text(docs, "doc_id", "text", "smallest").collect()} == {i: min(ids) for ids in groups.values() for i in ids}


def test_exact_index_by_levels(spark, docs, corpus):
    index = exact_dedup.DigestIndex.create(spark, fanout=2)
    for k in range(1, 6):
        index.flush(docs)
        index.compact()
        found = index.lookup([hashlib.sha256(b"a").digest(), bytes(32)]).collect()
        assert [(r.id, r.n) for r in found] == [(3, 2 * k)]
    assert [len(x) for x in index.levels] == [1, 0, 1]
    index.compact(whole=True)
    assert sum(map(len, index.levels)) == 1
    assert index.entries().count() == len({lower(t or "") for _, t, *_ in corpus})
    index.drop()


def test_filter_of_hits(spark):
    rows = spark.range(5000).select(F.unhex(F.sha2(F.col("id").cast("string"), 256)).alias("digest"), "id")
    hits = rows.where("id % 50 = 0").select("digest")
    got = {r.id for r in exact_dedup.passing(rows, hits, 100).collect()}
    assert {i for i in range(0, 5000, 50)} <= got and len(got) < 150


def test_dedup_goes_by_row(spark):
    """Rows that repeat an id with another text stay; rows equal in id and text leave one."""
    rows = [(1, "other", 1), (1, "a b c", 2), (2, "A b c", 3), (3, "z", 4), (3, "z", 4), (None, "z", 5), (None, "lone", 6), (None, "A B C", 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, row long")
    for f in (lambda d: exact_dedup.dedup(d, keep="smallest"), simhash.dedup):
        got = f(docs)
        assert got.columns == ["doc_id", "text", "row"]
        assert sorted((r.doc_id or 0, r.text) for r in got.collect()) == [(0, "lone"), (1, "a b c"), (1, "other"), (3, "z")]
    assert sorted((r.doc_id or 0, r.text) for r in exact_dedup.dedup(docs, keep="largest").collect()) == [(0, "lone"), (1, "other"), (2, "A b c"), (3, "z")]
    marked = exact_dedup.mark(docs, keep="largest").collect()
    assert len(marked) == 8 and sum(r.kept for r in marked) == 4
    assert sorted((r.doc_id or 0, r.keep_id, r.group_size) for r in marked if r.group_size > 1) == [(0, 2, 3), (0, 3, 3), (1, 2, 3), (2, 2, 3), (3, 3, 3), (3, 3, 3)]


def test_simhash(docs, corpus):
    got = {r.doc_id: r for r in simhash.near_duplicates(docs).collect()}
    prints = {}
    for i, t, *_ in corpus:
        w = words_of(lower(t or ""))
        shingles = [" ".join(w[j : j + 4]) for j in range(len(w) - 3)] or ([" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
        prints[i] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
        assert got[i].fingerprint == f"{prints[i]:016x}"
    parent = {i: i for i in prints}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in prints:
        for j in prints:
            if i < j and (prints[i] ^ prints[j]).bit_count() <= 4 and root(i) != root(j):
                parent[max(root(i), root(j))] = min(root(i), root(j))
    assert {i: r.component_id for i, r in got.items()} == {i: root(i) for i in prints}


def test_simhash_links_are_complete():
    rng = np.random.default_rng(1)
    centre = rng.integers(0, 1 << 64, 6, dtype=np.uint64)
    fp = np.array([c ^ np.uint64(sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 4), replace=False))) for c in centre for _ in range(250)])
    fp = np.unique(fp)[:, None]
    table = simhash.pivot_table(fp)
    parents = []
    for a, b in (simhash.connect_run(fp, table, 4), simhash.pairs_of_run(fp, table, 4)):
        parent = list(range(len(fp)))

        def root(i, parent=parent):
            while parent[i] != i:
                i = parent[i]
            return i

        for x, y in zip(a, b, strict=True):
            parent[root(int(x))] = root(int(y))
        parents.append([min(j for j in range(len(fp)) if root(j) == root(i)) for i in range(0, len(fp), 40)])
    assert parents[0] == parents[1]


def test_components(spark):
    pairs = [(i, i + 1) for i in range(1, 40)] + [(100, 60), (60, 61), (5, 5)]
    got = {r.node: r.component for r in components.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {**{i: 1 for i in range(1, 41)}, 60: 60, 61: 60, 100: 60}


def test_near_dedup_keeps_one(spark):
    rng = random.Random(9)
    base = text(rng, 400).split()
    rows = [(i, " ".join(base[: 40 * i] + ["new"] + base[40 * i + 1 :])) for i in range(5)] + [(10 + i, text(rng, 200)) for i in range(6)]
    assert sorted(r.doc_id for r in simhash.dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()) == [0, 10, 11, 12, 13, 14, 15]


def jaccard(a: str, b: str) -> float:
    x, y = ({tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} for w in (a.lower().split(), b.lower().split()))
    return len(x & y) / len(x | y)


def test_near_dedup_by_true_similarity(spark):
    """Pairs of similarity 0.7 to 0.9, lone and in one hot group, against all pairs."""
    rng = random.Random(21)
    texts = []
    for k in range(150):
        base = [str(rng.randrange(10**6)) for _ in range(rng.choice([12, 60, 204]))]
        n = len(base) - 4
        edge = round(n * (1 - rng.choice([0.70, 0.78, 0.79, 0.8, 0.81, 0.82, 0.9])))
        texts += [" ".join(base), " ".join(base[: len(base) - edge])]
    base = [str(rng.randrange(10**6)) for _ in range(104)]
    for k in range(120):  # copies of one text: far apart, at the edge, close
        w = list(base)
        for at in rng.sample(range(104), rng.choice([1, 2, 2, 3])):
            w[at] = f"new{k}"
        texts.append(" ".join(w))
    parent = list(range(len(texts)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(texts)):
        for j in range(i + 1, len(texts)) if i >= 300 else [i | 1]:
            if i != j and jaccard(texts[i], texts[j]) >= 0.8 and root(i) != root(j):
                parent[max(root(i), root(j))] = min(root(i), root(j))
    got = sorted(r.doc_id for r in simhash.dedup(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect())
    assert got == [i for i in range(len(texts)) if root(i) == i]


def test_decontamination(spark):
    rng = random.Random(2)
    items = [(i, text(rng, n)) for i, n in enumerate((30, 60, 12))] + [(3, None), (4, ""), (5, "zq")]
    one = items[1][1]
    edited = one[:50] + "X" + one[51:100] + one[102:]
    rows = [(0, text(rng, 300)), (1, text(rng, 50) + " " + items[0][1] + " " + text(rng, 50)), (2, text(rng, 20) + edited), (3, one.upper().replace(" ", "\n")), (4, None), (5, ""), (6, "zq"), (7, "zqx"), (1, items[2][1])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontaminate.leaks(docs, bench).collect()}
    assert got == {(1, 0), (2, 1), (3, 1), (6, 5), (1, 2)}
    small = decontaminate.LeakConfig(block_bytes=10)
    assert {(r.doc_id, r.item_id) for r in decontaminate.leaks(docs, bench, small).collect()} == got
    assert sorted(r.doc_id for r in decontaminate.clean(docs, bench).collect()) == [0, 4, 5, 7]


def test_decontamination_of_excerpts_and_replaced_words(spark):
    """Verbatim excerpts of 64 bytes at every offset; one word replaced in every 60 to 70 bytes; short items."""
    rng = random.Random(31)
    items = [(0, text(rng, 60)[:240]), (1, text(rng, 40)[:95]), (2, text(rng, 80)[:360])]
    rows = [(k, "zz yy. " + items[0][1][k : k + 64] + " xx ww") for k in range(240 - 63)]
    want = {(k, 0) for k in range(240 - 63)}
    for doc, item in ((1000, 1), (1001, 2)):
        t = items[item][1]
        for at in range(30, len(t) - 8, 66):
            t = t[:at] + "QZQZQZQ" + t[at + 7 :]
        rows.append((doc, "zz yy " + t + " xx"))
        want.add((doc, item))
    rows += [(2000 + k, text(rng, 200)) for k in range(50)]
    got = decontaminate.leaks(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    assert {(r.doc_id, r.item_id) for r in got.collect()} == want


def test_alignment():
    def edits(p, t):
        row = [0] * (len(t) + 1)
        for i, a in enumerate(p, 1):
            new = [i]
            for j, b in enumerate(t, 1):
                new.append(min(row[j - 1] + (a != b), row[j] + 1, new[-1] + 1))
            row = new
        return min(row)

    rng = random.Random(0)
    for _ in range(200):
        p, t = (bytes(rng.choice(b"abc") for _ in range(rng.randrange(1, 12))) for _ in range(2))
        got = decontaminate.align(p, t, 20)
        assert got[0] == edits(p, t)


def test_bpe_equals_the_library(docs, corpus):
    import tokenizers

    path = queries.tokenizer_path()
    library = tokenizers.Tokenizer.from_file(path)
    got = {r.doc_id: r for r in bpe.round_trip(docs, path).collect()}
    back = {r.doc_id: r.text for r in bpe.decode(bpe.encode(docs, path), path).collect()}
    for i, t, *_ in corpus:
        ids = library.encode(t or "", add_special_tokens=False).ids
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert back[i] == library.decode(ids, skip_special_tokens=False)


def test_bpe_random_texts():
    import tokenizers

    path = queries.tokenizer_path()
    library, own = tokenizers.Tokenizer.from_file(path), bpe.encoder(path)
    rng = random.Random(3)
    parts = ["the", " ", "  ", "\n", "\t", "é", "日本", "'ll", "'S", "123", "!!", "ing", "aaaaaa", "<|endoftext|>", "\x1c", "\x85", "\u3000"]
    texts = ["".join(rng.choice(parts) if rng.random() < 0.8 else chr(rng.randrange(32, 0xD000)) for _ in range(rng.randrange(30))) for _ in range(600)]
    for t, ids in zip(texts, own.encode_batch(texts), strict=True):
        assert ids == np.array(library.encode(t, add_special_tokens=False).ids, "<u4").tobytes()


@pytest.mark.parametrize("column", ["toxic", "quality"])
def test_factorisation_machine(spark, column):
    rng = random.Random(11)
    rows, labels = [], []
    for i in range(1200):
        bad = rng.random() < 0.3
        t = text(rng, rng.randint(20, 80)) + (f" {rng.choice(['moron', 'idiot'])} " if bad else " ") + text(rng, 5)
        rows.append((i, t if i else None))
        labels.append((i, int(bad), int(bad)))
    labels += [(5, None, None), (None, 1, 1), (7, 3, 3), (8, labels[8][1], labels[8][2])]
    docs, table = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in getattr(classifiers, "toxicity" if column == "toxic" else "quality")(docs, table).collect()}
    assert len(got) == 1200 and all(0 <= r.score <= 1 for r in got.values())
    held = [i for i in range(1, 1200) if got[i].held_out]
    assert 150 < len(held) < 330
    assert np.mean([got[i].predicted == labels[i][1] for i in held]) > 0.95


@pytest.mark.parametrize("config", [classifiers.QUALITY, classifiers.TOXICITY])
def test_interaction_without_marginal_evidence(spark, config):
    """The label says whether exactly one of two words is there: neither word tells anything alone."""
    rng = random.Random(8)
    filler = ["".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(300)]
    rows, labels = [], []
    for i in range(3600):
        a, b = rng.random() < 0.5, rng.random() < 0.5
        w = [rng.choice(filler) for _ in range(40)]
        w[3], w[9] = ("alpha" if a else w[3]), ("beta" if b else w[9])
        rows.append((i, " ".join(w)))
        labels.append((i, int(a != b), int(a != b)))
    docs, table = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = [r for r in classifiers.judge(docs, table, "toxic", 0.5, config).collect() if r.held_out]
    assert np.mean([r.predicted == labels[r.doc_id][2] for r in got]) > 0.95


def test_classifier_without_labels(spark, docs):
    nothing = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {round(r.score, 3) for r in classifiers.toxicity(docs, nothing).collect()} == {0.5}


def test_language(spark):
    rng = random.Random(5)
    sounds = {"aa": "the ing tion er".split(), "bb": "eau oi les aux".split(), "cc": "ción rr ez ñ".split()}
    rows = [(i, " ".join("".join(rng.choice(sounds[l]) for _ in range(3)) for _ in range(30)), l) for i, l in enumerate(rng.choice(list(sounds)) for _ in range(300))]
    rows += [(1000, None, "aa"), (1001, "12 !!", "bb"), (1002, "", None), (1003, "theing", None), (1004, "٣٤", "aa")]
    got = {r.doc_id: r for r in langid.language(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert all(got[i].lang_pred == l for i, _, l in rows[:300])
    assert [got[i].lang_pred for i in (1000, 1001, 1002, 1003, 1004)] == ["und", "und", "und", "aa", "und"]


def test_many_languages(spark):
    """More languages than one word has bits."""
    rng = random.Random(6)
    names = [f"l{k:03d}" for k in range(130)]
    sounds = {l: ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(4)) for _ in range(12)] for l in names}
    rows = [(i, " ".join(rng.choice(sounds[l]) for _ in range(30)), l) for i, l in enumerate(names * 6)]
    got = {r.doc_id: r for r in langid.language(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert np.mean([got[i].lang_pred == l for i, _, l in rows]) > 0.97


def test_urls(spark):
    rows = [
        (0, "http://A.example.ORG/es/1?x"), (1, "https://example.org/en/12"), (2, "https://example.org/en/2"), (3, "http://x.com/fr/a#b"), (4, "http://x.com/de/"), (5, None), (6, "no scheme"),
        (7, "http://casinowin.example.net/en/3"), (8, "http://quietpage.example.net/en/3"), (9, "http://badexample.org/es/1"), (10, "x://"), (11, "http://h?q"), (12, "http://com.net/de/"),
    ] + [(100 + i, f"http://quiet.page{i}.example.net/en/{i}") for i in range(30)]
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge(spark.createDataFrame(rows, "page_id long, url string")).collect()}
    assert got[0] == ("a.example.org", "/es/1", "example.org/es/", "block")
    assert got[1][2:] == ("example.org/en/1", "block")
    assert got[2][2:] == ("org/", "allow")
    assert got[3] == ("x.com", "/fr/a", "com/fr/", "allow")
    assert got[4][2:] == ("com/de/", "block")
    assert got[5] == got[6] == ("", "", None, "allow")
    assert got[7][2:] == (None, "block") and got[8][2:] == (None, "allow")
    assert got[9][2] == "org/" and got[10][:3] == ("", "", None) and got[11][:2] == ("h", "") and got[12][2] is None
    model = urls.fit(spark.createDataFrame(rows, "page_id long, url string"))
    assert model.segment("casinowin") == ["casino", "win"]


@pytest.mark.parametrize("size", [300, 9000])
def test_urls_with_a_frequent_joined_host(spark, size):
    """A third of all rows has one unwanted joined name; frequent ordinary names stay whole."""
    host = F.when(F.col("id") % 3 == 0, "casinowin").when(F.col("id") % 3 == 1, "essex").otherwise("quiet")
    pages = spark.range(size).select(F.col("id").alias("page_id"), F.concat(F.lit("http://"), host, F.lit(".example.net/en/"), "id").alias("url"))
    got = {(r.host, r.verdict) for r in urls.judge(pages).select("host", "verdict").distinct().collect()}
    assert got == {("casinowin.example.net", "block"), ("essex.example.net", "allow"), ("quiet.example.net", "allow")}
    assert urls.fit(pages).segment("casinowin") == ["casino", "win"]


def test_fold(spark):
    import zlib

    rows = spark.range(200).select("id", fold(__import__("pyspark").sql.functions.col("id"), 5).alias("f")).collect()
    assert all(r.f == zlib.crc32(str(r.id).encode()) % 5 for r in rows)


def test_empty_tables(spark, none):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    bench = spark.createDataFrame([], "item_id long, text string")
    results = [
        debruijn.dedup(none), suffix_dedup.dedup(none), exact_dedup.mark(none), exact_dedup.dedup(none), simhash.near_duplicates(none), simhash.dedup(none), decontaminate.leaks(none, bench), decontaminate.clean(none, bench),
        bpe.round_trip(none, queries.tokenizer_path()), classifiers.toxicity(none, labels), classifiers.keep_quality(none, labels), langid.language(none), urls.judge(spark.createDataFrame([], "page_id long, url string")),
    ]
    assert [r.count() for r in results] == [0] * len(results)


def test_null_ids(spark):
    rows = [(None, "a b c " * 30), (1, "a b c " * 30), (None, None), (1, "a b c " * 30), (1, "other")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert debruijn.dedup(docs).count() == suffix_dedup.dedup(docs).count() == exact_dedup.mark(docs).count() == simhash.near_duplicates(docs).count() == 5
    assert bpe.round_trip(docs, queries.tokenizer_path()).count() == langid.language(docs.selectExpr("*", "'xx' AS lang")).count() == 5
    got = sorted((r.doc_id or 0, r.n_words, r.n_removed) for r in debruijn.dedup(docs).collect())
    assert [g[:2] for g in got] == [(0, 0), (0, 90), (1, 1), (1, 90), (1, 90)] and [g[2] for g in got][2:] == [0, 90, 90]


def test_hot_runs_give_a_forest_of_labels(spark):
    """Similar members of few labels: one link joins two labels, however many pairs of members are similar."""
    words = [f"w{i}" for i in range(200)]
    rows = [(i, " ".join([*words[: 2 * i], f"x{i}", *words[2 * i + 1 :]])) for i in range(70)]
    docs = spark.createDataFrame(rows, "id long, text string")
    members = simhash.sketches(docs).withColumnRenamed("id", "rep").selectExpr("rep", "n", "fp", "keys", "CASE WHEN rep < 40 THEN 0L WHEN rep < 68 THEN 40L ELSE rep END AS label")
    got = {(r.a, r.b) for r in simhash.links_of_hot_runs(members, docs).collect()}
    labels = {0, 40, 68, 69}
    assert {x for pair in got for x in pair} == labels and len(got) <= 6
    links = spark.createDataFrame([(41, 3), (42, 2), (45, 1), (90, 91)], "a long, b long")
    before = spark.createDataFrame([(i, 0 if i < 40 else 40) for i in range(60)], "node long, component long")
    after = {r.node: r.component for r in components.extended(before, links).collect()}
    assert after == {**{i: 0 for i in range(60)}, 90: 90, 91: 90}
