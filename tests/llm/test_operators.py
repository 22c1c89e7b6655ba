"""The operators on small tables with nulls, empty and long texts, repeats and clashing columns, against brute force."""

import hashlib
import math
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F, types as T

from flowmatch.llm import bpe, embedding_dedup, language_id, lm_scoring, minhash, mixing, quality_classifier, quality_rules, quotation, sharding
from flowmatch.llm.queries import tokenizer
from flowmatch.llm.tokens import Tokens

LONG = "lorem ipsum dolor " * 3000
TEXTS = ["alpha beta gamma delta epsilon zeta eta theta", "alpha beta gamma delta epsilon zeta eta theta", "", None, LONG, "x", "Ärger über Öl", "a  b\n\na  b\n\tc", "one two three one two three!!", "#*$ %& |<> ²½ \x1c\x85 it's"]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id string, t int, size string, key double"


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, ["en", "de", None][i % 3], ["s", "t", None][i % 3], 1, "x", 1, "y", 0.5) for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows + [rows[0], (None, None, None, None, None, None, None, None, None)], SCHEMA)


def test_bpe_equals_tiktoken(docs):
    import tiktoken

    path, pattern = tokenizer()
    ranks = bpe.read_ranks(path)
    own = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    coded = bpe.encode(docs, path, pattern).collect()
    want = Counter((i, tuple(own.encode_ordinary(t or ""))) for i, t in [*enumerate(TEXTS), (0, TEXTS[0]), (None, None)])
    assert Counter((r.doc_id, tuple(r.ids)) for r in coded) == want
    for word in ("a" * 700, "zqxj" * 90, "\U0001f600" * 20, "don't've"):
        made = bpe.codec(path, pattern)
        assert made.encode(word).tolist() == own.encode_ordinary(word) and made.decode(made.encode(word)) == word.encode()
    assert bpe.round_trip(docs.limit(0), path, pattern).count() == 0


def test_perfect_hash_is_minimal():
    keys = [str(i).encode() for i in range(5000)]
    h = bpe.PerfectHash(keys)
    assert sorted(h.slot_of.tolist()) == list(range(5000)) and all(h.keys[s] == k for s, k in zip(h.slots(keys), keys))


def test_rule_counts():
    def brute(text):
        w = (text or "").encode().split()
        seen = Counter(zip(w, w[1:], w[2:]))
        hit = {i + k for i in range(len(w) - 2) if seen[tuple(w[i : i + 3])] > 1 for k in range(3)}
        lines = [x for x in (text or "").split("\n") if x.encode().split()]
        return len(w), sum(len(x.decode()) for x in w), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(hit)

    from flowmatch.llm.textstats import rule_counts

    for t in [*TEXTS, "a b c a b c a b", "q q q q"]:
        assert rule_counts((t or "").encode())[:5] == brute(t)


def test_rules_and_classifier_tell_junk(spark):
    rng = np.random.default_rng(1)
    word = lambda: "".join(rng.choice(list("aeionrst"), 5))
    rows = [(i, " ".join(word() + ("" if i % 5 else "&&%%") for _ in range(80)) + ".") for i in range(300)]
    docs = spark.createDataFrame([*rows, (None, None), (999, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 5 != 0)) for i in range(200)] + [(3, None), (None, 1)], "doc_id long, quality int")
    out = {r.doc_id: r for r in quality_rules.judge(docs, labels).collect()}
    assert all(out[i].kept == (i % 5 != 0) for i in range(300)) and out[999].base_failed and out[None].base_failed
    model = quality_classifier.fit(docs, labels)
    score = {r.doc_id: r.score for r in quality_classifier.score(docs, model).collect()}
    assert all((score[i] >= 0.7) == (i % 5 != 0) for i in range(300)) and 0 <= score[999] <= 1
    assert quality_classifier.fit(docs, labels.limit(0)).score([b"a"], Tokens())[0] == 0.5


def test_language(spark, docs):
    en, de = "the and with thing tion of house ", "der und ich schön ung Straße über "
    rows = [(i, (en if i % 2 else de) * (1 + i % 7), "en" if i % 2 else "de") for i in range(40)]
    model = language_id.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    got = dict(zip(range(5), zip(*model.predict(["with the thing", "Straße und ich", None, "123 !!", ""]))))
    assert [got[i][0] for i in range(5)] == ["en", "de", "und", "und", "und"] and all(0 <= s <= 1 for _, s in got.values())
    assert language_id.identified(docs, model).columns == docs.columns
    assert language_id.fit(docs.limit(0)).predict(["abc"])[0] == ["und"]


def test_darts_estimate_jaccard():
    rng = np.random.default_rng(0)
    x = np.unique(rng.integers(0, 2**62, 400).astype(np.uint64))
    w, v = rng.integers(1, 9, len(x)).astype(float), rng.integers(1, 9, len(x)).astype(float)
    true = np.minimum(w, v).sum() / np.maximum(w, v).sum()
    est = np.mean([np.mean(minhash.darts(minhash._mix(x + np.uint64(i)), w) == minhash.darts(minhash._mix(x + np.uint64(i)), v)) for i in range(12)])
    assert abs(est - true) < 0.05


@pytest.mark.parametrize("small, tile, weights", [(16, 1024, "count"), (2, 3, "count"), (2, 3, "set")])
def test_near_duplicates(spark, monkeypatch, small, tile, weights):
    monkeypatch.setattr(minhash, "SMALL", small)
    monkeypatch.setattr(minhash, "TILE", tile)
    rng = np.random.default_rng(3)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(40):
        words = list(base) if i % 2 else [f"v{k}" for k in range(100)]
        for k in rng.choice(len(words), int(rng.integers(0, 5)), replace=False):
            words[k] = f"n{i}_{k}"
        rows.append((i, " ".join(words)))
    rows += [(100, "short text"), (101, "short  text"), (102, ""), (103, None), (None, "short text"), (0, rows[0][1])]
    rows += [(200, "again and again we say it " * 40), (201, "again and again we say it " * 34), (202, "again and again we say it " * 20)]
    grams = {i: Counter(zip(*[t.split()[k:] for k in range(5)])) for i, t in rows[:40] + rows[-3:]}
    if weights == "set":
        grams = {i: Counter(set(g)) for i, g in grams.items()}
    root = {i: i for i in grams}
    for a in grams:
        for b in grams:
            if b < a and (grams[a] & grams[b]).total() / (grams[a] | grams[b]).total() >= 0.8:
                x, y = root[a], root[b]
                root = {k: min(x, y) if v in (x, y) else v for k, v in root.items()}
    assert (root[202] == 200) == (weights == "set") and root[201] == 200
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in minhash.classes(docs, weights=weights).collect()}
    assert {i: got[i] for i in grams} == root and got[100] == got[101] == 100 and got[102] == 102 and got[103] == 103
    kept = minhash.deduplicated(docs, weights=weights)
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == sorted([*set(root.values()), 100, 102, 103])


@pytest.mark.parametrize("tile, span", [(128, 16), (8, 2)])
def test_embeddings(spark, monkeypatch, tile, span):
    monkeypatch.setattr(embedding_dedup, "TILE", tile)
    monkeypatch.setattr(embedding_dedup, "SPAN", span)
    rng = np.random.default_rng(5)
    base = rng.standard_normal((6, 16))
    v = [(i, (base[i % 6] + rng.standard_normal(16) * 0.09).tolist()) for i in range(60)]
    v += [(60, v[0][1]), (61, None), (62, [0.0] * 16), (63, [float("nan")] * 16), (64, [None] + [1.0] * 15), (65, [1.0, 2.0]), (66, [])]
    got = {r.vec_id: r for r in embedding_dedup.near_duplicates(spark.createDataFrame(v, "vec_id long, embedding array<double>")).collect()}
    x = np.array([e for _, e in v[:61]])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    link = x @ x.T >= 0.95
    np.fill_diagonal(link, False)
    i, j = np.nonzero(link)
    root = embedding_dedup._forest(61, i, j)
    assert [got[k].n_links for k in range(61)] == link.sum(axis=1).tolist() and [got[k].component_id for k in range(61)] == root.tolist()
    assert all(got[k].n_links == 0 and got[k].kept for k in range(61, 67))


def test_mixing(docs, spark, monkeypatch):
    monkeypatch.setattr(mixing, "EDGE_ROWS", 3)
    out = mixing.mix(mixing.drawn(docs)).collect()
    sums = Counter()
    for r in out:
        sums[r.source] += r["size"]
        assert r.taken <= 3 * r["size"] and (r["size"] == 0 or r.taken % r["size"] == 0)
    assert all(r.source_size == sums[r.source] and r.target <= 3 * r.source_size for r in out) and len(out) == docs.count()
    many = spark.createDataFrame([(i, "w " * (1 + i % 9), "ab"[i % 2]) for i in range(2000)], "doc_id long, text string, source string")
    got = mixing.mix(mixing.drawn(many)).groupBy("source").agg(F.sum("taken").alias("n"), F.first("target").alias("t")).collect()
    assert all(abs(r.n - r.t) <= 9 for r in got)
    want = {r.doc_id: r.taken for r in mixing.mix(mixing.drawn(many)).collect()}
    for most in (1, 6):  # sources meet their documents by salt, cuts end early: the same result
        monkeypatch.setattr(mixing, "MOST_CUTS", most)
        monkeypatch.setattr(mixing, "BROADCAST_SOURCES", 0)
        assert {r.doc_id: r.taken for r in mixing.mix(mixing.drawn(many)).collect()} == want
    # A third of all rows repeat one id: in or out together.
    same = spark.createDataFrame([(7 if i % 3 == 0 else i, "w w", "ab"[i % 2]) for i in range(900)], "doc_id long, text string, source string")
    assert all(r.n == 1 for r in mixing.mix(mixing.drawn(same)).groupBy("doc_id", "source").agg(F.count_distinct("taken").alias("n")).collect())
    assert mixing.repeated(docs).columns == docs.columns and mixing.mix(mixing.drawn(docs.limit(0))).count() == 0


def test_sharding(spark, docs, monkeypatch):
    many = spark.createDataFrame([(i, "t" * (i % 7)) for i in range(6000)], "doc_id long, text string")
    rows = sharding.place(many).collect()
    by = {}
    for r in rows:
        by.setdefault(r.shard, []).append(r.slot)
        assert r.grown_shard in (r.shard, 40) and r.text_crc32 == zlib.crc32(("t" * (r.doc_id % 7)).encode()) and r["size"] == 16 + r.doc_id % 7
    assert sorted(by) == list(range(40)) and all(sorted(s) == list(range(len(s))) for s in by.values())
    assert 50 < sum(r.grown_shard == 40 for r in rows) < 300
    def best(key, n):
        m = hashlib.md5(str(key).encode()).hexdigest()
        x, y = (int(m[8 * k : 8 * k + 8], 16) % (1 << 30) for k in range(2))
        p = sharding.PRIME
        u = [(((x * a + y) % p) * ((y * b + x) % p) + c) % p for a, b, c in map(sharding._factors, range(n))]
        return max(range(n), key=lambda s: (u[s], s))

    assert all((r.shard, r.grown_shard) == (best(r.doc_id, 40), best(r.doc_id, 41)) for r in rows)
    monkeypatch.setattr(sharding, "ROWS_PER_PART", 50)
    equal = sharding.place(spark.createDataFrame([(5, "x")] * 333 + [(None, None)] * 2, "doc_id long, text string"), 3).collect()
    assert sorted(r.slot for r in equal if r.doc_id == 5) == list(range(333)) or len({r.shard for r in equal}) == 1 and sorted(r.slot for r in equal) == list(range(335))
    heavy = Counter(r.s for r in many.select(sharding.shard_of(F.col("doc_id"), 2, [3.0, 1.0]).alias("s")).collect())
    assert abs(heavy[0] / 6000 - 0.75) < 0.03 and sharding.place(docs).count() == docs.count()


def test_language_model(docs):
    out = {r.doc_id: r for r in lm_scoring.scored(docs, F.coalesce(F.col("doc_id"), F.lit(1)) % 4 != 1).collect()}
    tokens = lambda t: (t or "").encode().lower().split() + [None]
    train = Counter(w for i, t in [*enumerate(TEXTS), (0, TEXTS[0])] if i % 4 != 1 for w in tokens(t))
    n, v = sum(train.values()), len(train)
    for i, t in enumerate(TEXTS):
        base = sum(math.log10((train[w] + 0.5) / (n + 0.5 * (v + 1))) for w in tokens(t))
        assert out[i].n_tokens == len(tokens(t)) and out[i].train_tokens == n and out[i].n_known == sum(train[w] > 0 for w in tokens(t))
        assert out[i].base_score == pytest.approx(base, rel=1e-9) and out[i].score <= 0
    assert out[4].score > out[4].base_score


def test_language_model_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(lm_scoring, "CHUNK", 1 << 17)
    monkeypatch.setattr(lm_scoring, "BLOCK_BYTES", 1 << 16)
    # 400,000 tokens, of which a word of 3 has less than a 65,536th: it takes part in bigrams all the same.
    rows = [(k, "common " * 4000) for k in range(100)] + [(200 + k, "rare couple") for k in range(3)] + [(300, "rare couple"), (301, "couple rare"), (302, "Once common")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in lm_scoring.scored(docs, F.col("doc_id") < 300).collect()}
    texts = [t.lower().split() + [None] for i, t in rows if i < 300]
    one, two = Counter(w for t in texts for w in t), Counter(p for t in texts for p in zip(t, t[1:]))
    n, v = sum(one.values()), len(one)
    edge = lambda c: math.ceil(2 ** (math.floor(2 * math.log2(c) + 1e-9) / 2) - 1e-6) if c >= lm_scoring.LEAST else 0
    share = lambda w: (one[w] + 0.5) / (n + 0.5 * (v + 1))

    def want(text):
        t = text.lower().split() + [None]
        out = math.log10(share(t[0]))
        for a, b in zip(t, t[1:]):
            out += math.log10((1 - lm_scoring.SHARE) * share(b) + lm_scoring.SHARE * min(edge(two[a, b]), one[a], one[b]) / one[a] if one[a] else share(b))
        return out

    assert all(got[i].score == pytest.approx(want(t), rel=1e-9) for i, t in rows)
    assert got[300].score > got[300].base_score + 2 and {r.train_tokens for r in got.values()} == {n}


def test_filter_keeps_levels():
    rng = np.random.default_rng(4)
    keys = np.unique(rng.integers(0, 2**32, 20_000).astype(np.uint64))
    counts = rng.integers(0, 40, len(keys))
    level = lm_scoring.level_of(counts)
    read = lm_scoring.Bloom(keys[level >= 0], level[level >= 0]).level(keys)
    assert (read >= level).all() and (read != level).mean() < 0.01
    assert [int(lm_scoring.edge(x)) for x in lm_scoring.level_of(np.array([1, 2, 3, 4, 5, 6, 8]))] == [0, 2, 3, 4, 4, 6, 8]


def test_quotations(spark):
    rows = [(1, 0, "u", "Hello there\nsecond"), (1, 1, "a", "> hello  there\n> second\nreply"), (1, 2, "u", ">> hello there\n>> second\n> Reply\nthird"), (2, 0, "u", "> third\nforeign"), (3, 0, None, None), (None, 1, "u", "> x"), (1, 1, "a", "> hello  there\n> second\nreply")]
    out = [r for r in quotation.conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()]
    got = {(r.conv_id, r.turn): r for r in out}
    assert len(out) == len(rows) and (got[1, 1].parent_turn, got[1, 2].parent_turn, got[2, 0].parent_conv, got[2, 0].thread_id, got[2, 0].hops) == (0, 1, 1, 1, 3)
    assert got[1, 2].body == "third" and got[1, 2].n_linked == 2 and got[1, 2].quote_depth == 2 and sorted(r.position for r in out if r.thread_id == 1) == [0, 1, 2, 3, 4]


def test_quotations_of_parts(spark):
    squeezed = lambda x: " ".join(x.lower().split())
    rows = [
        (1, 0, "u", "one\ntwo\nThree\nfour\n\nfive\nsix\n\nseven"),
        (1, 1, "a", "> two\n> three\nlines of a paragraph, said at length"),
        (1, 2, "u", "> one two\n> three four\n>\n> five\n> six\nparagraphs, wrapped anew"),
        (1, 3, "a", "> lines of a paragraph, said at length\nA1\nA2\n\n> paragraphs, wrapped anew\nB1\nB2"),
        (1, 4, "u", "> A1\n> A2\nyes\n> B1 B2\nno"),
        (1, 5, "u", "> two\n> four\nnot consecutive"),
        (1, 6, "u", "> two\n> three\n> four\n>\n> five\n> eight\nends otherwise"),
        (2, 0, "u", "> Six\n>\n> seven\nfrom afar"),
    ]
    out = {(r.conv_id, r.turn): r for r in quotation.conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    said = {(c, t): squeezed(" ".join(x for x in text.split("\n") if not x.startswith(">"))) for c, t, _, text in rows}

    def parent(c, t, text):
        """The earliest message in its own conversation, else of all, whose words hold those of the first passage."""
        quote = []
        for line in text.split("\n"):
            if line.startswith(">"):
                quote.append(line[1:])
            elif quote:
                break
        quote = f" {squeezed(' '.join(quote))} "
        near = [k for k in sorted(said) if k < (c, t) and quote in f" {said[k]} "]
        return next((k for k in near if k[0] == c), near[0] if near else (None, None))

    for c, t, _, text in rows[1:]:
        assert (out[c, t].parent_conv, out[c, t].parent_turn) == parent(c, t, text), (c, t)
    assert out[1, 4].n_passages == out[1, 4].n_linked == 2 and out[1, 4].parent_turn == 3 and out[2, 0].parent_conv == 1 and out[1, 5].n_linked == out[1, 6].n_linked == 0


def test_every_language_and_letter_is_learnt(spark, monkeypatch):
    monkeypatch.setattr(language_id, "LANDMARKS", 8)
    # 70 languages of 20 letters each of one large script: more than 64 languages, 1,400 letters.
    rng = np.random.default_rng(2)
    text = lambda k: " ".join("".join(chr(0x4E00 + 20 * k + int(c)) for c in rng.integers(0, 20, 6)) for _ in range(12))
    rows = [(100 * k + i, text(k), f"l{k}") for k in range(70) for i in range(3)]
    model = language_id.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert model.langs == sorted(f"l{k}" for k in range(70)) and model.predict([text(k) for k in range(70)])[0] == [f"l{k}" for k in range(70)]
    sets = [{t.lower()[i : i + n] for n in (1, 2, 3) for i in range(len(t) - n + 1)} for t in ("a bc", "ab ab \u4e00")]
    assert [len(language_id.grams(t)) for t in ("a bc", "ab, ab \u4e00")] == [len(x) for x in sets]


def test_forest_against_brute_force():
    rng = np.random.default_rng(8)
    rows = rng.standard_normal((300, 4))
    forest = quality_rules.IsolationForest(rows, trees=20, per_tree=64)

    def path(tree, row):
        measure, value, child, length = tree
        at = 0
        while measure[at] >= 0:
            at = child[at] + (row[measure[at]] >= value[at])
        return length[at]

    expected = lambda n: 2 * sum(1 / k for k in range(1, n)) - 2 * (n - 1) / n
    far = np.vstack([rows[:50], np.full((1, 4), 9.0)])
    want = [2 ** (-np.mean([path(t, r) for t in forest.trees]) / expected(64)) for r in far]
    assert forest.score(far) == pytest.approx(want, rel=0.01) and forest.score(far)[-1] > max(want[:-1])


def test_held_out_accuracy(spark, sf):
    from flowmatch.llm import queries
    from flowmatch.llm.common import table

    labels = {r.doc_id: r.quality for r in table(spark, sf, "labels").collect()}
    got = [(r.predicted, labels[r.doc_id]) for r in queries.op4_quality_classifier(spark, sf).collect() if r.held_out and r.doc_id in labels]
    assert np.mean([a == b for a, b in got]) >= 0.85
    lang = {r.doc_id: r.lang for r in table(spark, sf, "documents").collect()}
    got = [(r.lang_pred, lang[r.doc_id]) for r in queries.op9_language_id(spark, sf).collect() if r.held_out and lang[r.doc_id]]
    assert np.mean([a == b for a, b in got]) >= 0.95
    lm = [r for r in queries.op8_lm_scoring(spark, sf).collect() if r.held_out]
    assert sum(r.score for r in lm) > sum(r.base_score for r in lm)


def test_kernel_against_brute_force():
    texts = ["the thing of the house", "die Straße und das Haus", "the house", "und das"]
    model = language_id.Nystroem(texts, ["en", "de", "en", "de"])

    def grams(t):
        x = "".join(c if c.isalpha() else " " for c in t.lower())
        x = " ".join(x.split()) if x == x.strip() else x
        return {x[i : i + n] for n in (1, 2, 3) for i in range(len(x) - n + 1)}

    order = sorted(range(4), key=lambda i: -len(language_id.grams(texts[i])))
    rank, marks = Counter(), []
    for i in order:
        rank["ende"[2 * (i % 2) :][:2]] += 1
        marks.append((rank["ende"[2 * (i % 2) :][:2]], ["en", "de"][i % 2], i))
    marks = [i for *_, i in sorted(marks)]
    for t in ("the Haus", "of"):
        want = [len(grams(t) & grams(texts[i])) / math.sqrt(len(grams(t)) * len(grams(texts[i]))) for i in marks]
        assert model._kernel([language_id.grams(t)])[0] == pytest.approx(want)


EMPTY = {"documents": "doc_id long, text string, lang string, source string, n_chars long", "labels": "doc_id long, quality int, toxic int", "embeddings": "vec_id long, embedding array<float>, label int", "conversations": "conv_id long, turn long, role string, text string"}
CLASH = "id, t, l, s, k, h, v, key, chunk, block, words, pairs, size, source_size, target, weight, score, rep, a, b, c, n, at, cell, tile, pass, role2, part, train, m, q, word, count, component, pivot, bands"


@pytest.mark.parametrize("kind", ["empty", "clashing"])
def test_queries_on_empty_and_clashing_tables(spark, sf, tmp_path, kind):
    from flowmatch.llm import queries

    for name, schema in EMPTY.items():
        df = spark.createDataFrame([], schema)
        if kind == "clashing":
            df = spark.read.parquet(f"{sf}/{name}.parquet").limit(60)
            extra = [c for c in CLASH.split(", ") if c not in df.columns]
            df = df.withColumns({c: F.lit("x") for c in extra})
            df = df.unionByName(df.limit(2)).unionByName(spark.createDataFrame([(None,) * len(df.columns)], T.StructType([T.StructField(f.name, f.dataType) for f in df.schema])))
        df.write.parquet(f"{tmp_path}/{name}.parquet")
    for name, query in queries.queries().items():
        rows = query(spark, str(tmp_path)).collect()
        table = "embeddings" if "op1_" in name else "conversations" if "op5" in name else "documents"
        assert name == "pipeline" or len(rows) == spark.read.parquet(f"{tmp_path}/{table}.parquet").count(), name
