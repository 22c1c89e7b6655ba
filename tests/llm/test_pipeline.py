import base64
import hashlib
from collections import Counter

import corpus_pipeline
from pyspark.sql import functions as F

from flowmatch.llm import language_id, quality_classifier
from flowmatch.llm.common import fold, table


def test_stages_on_small_data(spark, sf):
    rows = spark.read.parquet(f"{sf}/documents.parquet")
    out = corpus_pipeline.run(spark, sf)
    n = out.count()
    assert [n for n, _ in corpus_pipeline.STAGES] and 0 < n <= 3 * rows.count() and corpus_pipeline.ORACLE_SQL is None
    assert "ids_sha256" in out.columns


def test_language_stage_drops_what_is_not_learnt(spark, sf):
    docs = table(spark, sf, "documents")
    first = docs.first().asDict()
    strange = ["\u041f\u0440\u0438\u0432\u0435\u0442 \u043c\u0438\u0440, \u043a\u0430\u043a \u0434\u0435\u043b\u0430", base64.b64encode(hashlib.sha512(b"x").digest() * 9).decode(), "x 1 2 3 4", "\u65e5\u672c\u8a9e\u306e\u30c6\u30ad\u30b9\u30c8"]
    more = spark.createDataFrame([tuple((first | {"doc_id": -1 - i, "text": t, "lang": None}).values()) for i, t in enumerate(strange)], docs.schema)
    kept = {r.doc_id for r in corpus_pipeline.identify_language(spark, docs.unionByName(more), sf).collect()}
    assert not kept & {-1, -2, -3, -4}
    rows = docs.collect()
    model = language_id.fit(docs.where(fold(docs.doc_id, 4) != 2))
    name, score = model.predict([r.text for r in rows])
    assert {r.doc_id for r, n, v in zip(rows, name, score) if n != "und" and v >= model.least} == kept
    clean = [r.doc_id for r in rows if r.lang is not None and language_id.has_letter(r.text)]
    assert 0 < model.least < 0.5 and len(set(clean) - kept) <= 0.01 * len(clean)


def test_stages_against_brute_force(spark, sf):
    docs = table(spark, sf, "documents").limit(60)
    grams = lambda t: frozenset(zip(*[(t or "").encode().split()[k:] for k in range(5)]))
    # Near-duplicates: one of each class of the transitive closure of Jaccard >= 0.8; shorter texts are compared by their words.
    rows = [r for r in docs.collect() if len((r.text or "").split()) >= 5]
    long = spark.createDataFrame(rows, docs.schema)
    root = list(range(len(rows)))
    sets = [grams(r.text) for r in rows]
    for a in range(len(rows)):
        for b in range(a):
            if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                x, y = root[a], root[b]
                root = [min(x, y) if v in (x, y) else v for v in root]
    kept = corpus_pipeline.remove_near_duplicates(spark, long, sf).collect()
    place = {r.doc_id: k for k, r in enumerate(rows)}
    assert Counter(root[place[r.doc_id]] for r in kept) == Counter(set(root))
    # Quality: the rows whose score reaches the bar, one by one.
    labels = table(spark, sf, "labels").where(fold(F.col("doc_id"), 4) != 2)
    scores = {r.doc_id: r.score for r in quality_classifier.score(docs, quality_classifier.fit(docs, labels)).collect()}
    assert sorted(r.doc_id for r in corpus_pipeline.classify_quality(spark, docs, sf).collect()) == sorted(k for k, v in scores.items() if v >= quality_classifier.ACCEPT)
    # Mixing: copies of whole rows, none more than three times.
    mixed = Counter(r.doc_id for r in corpus_pipeline.mix_sources(spark, long, sf).collect())
    assert set(mixed) <= set(place) and max(mixed.values()) <= 3
