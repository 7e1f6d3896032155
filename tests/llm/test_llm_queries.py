"""The registered queries and the pipeline on small tables."""

import math

import duckdb
import pytest

import corpus_pipeline
from evenpick.llm import mix, neardup, pseudonym, quality
from evenpick.llm.queries import DEMONSTRATION_KEY, ORACLES, PIECE_MODEL, QUERIES


def plain(rows, names):
    text = lambda v: "null" if v is None or (isinstance(v, float) and math.isnan(v)) else f"{v:.7g}" if isinstance(v, float) else str(v)
    return sorted(tuple(text(r[c]) for c in sorted(names)) for r in rows)


@pytest.mark.parametrize("name", list(ORACLES))
def test_against_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "conversations", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    cur = con.execute(ORACLES[name])
    names = [c[0] for c in cur.description]
    rows = [r.asDict() for r in QUERIES[name](spark, sf).collect()]
    assert set(rows[0]) == set(names)
    assert plain(rows, names) == plain([dict(zip(names, r)) for r in cur.fetchall()], names)


def test_pipeline_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    before = {r.doc_id for r in docs.select("doc_id").collect()}
    kept = docs
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES[:-1]):
        out = stage(spark, kept, sf).cache()
        assert out.columns == docs.columns, name
        ids = {r.doc_id for r in out.select("doc_id").collect()}
        assert ids <= before
        before, kept = ids, out
    last = corpus_pipeline.STAGES[-1][1](spark, kept, sf)
    assert last.count() == kept.count()
    assert corpus_pipeline.run(spark, sf).count() == kept.count()


def test_pipeline_on_an_empty_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
    assert docs.count() == 0


def keyed(rows):
    return sorted(((r.doc_id, r.text) for r in rows), key=str)


def test_pipeline_stages_against_plain_versions(spark, sf):
    """Every stage's rows recomputed outside Spark from the rows it was given."""
    import hashlib

    import numpy as np
    import pyarrow as pa
    import sentencepiece

    docs = spark.read.parquet(f"{sf}/documents.parquet").cache()
    stages = [s for _, s in corpus_pipeline.STAGES]
    labels = spark.read.parquet(f"{sf}/labels.parquet")

    rows = docs.collect()
    model = quality.train_quality(docs, labels)
    good = model.score(quality.text_features(pa.array([r.text for r in rows], pa.string()))) >= corpus_pipeline.QUALITY_FLOOR
    kept = stages[0](spark, docs, sf).cache()
    assert keyed(kept.collect()) == keyed([r for r, ok in zip(rows, good) if ok]) and 0 < good.sum() < len(rows)

    rows = kept.collect()
    sets = [set(s.tolist()) for s in neardup.shingle_sets(pa.array([r.text for r in rows], pa.string()))]
    root = {r.doc_id: r.doc_id for r in rows}
    find = lambda x: x if root[x] == x else find(root[x])
    for i, a in enumerate(sets):
        for j in range(i):
            if (both := len(a & sets[j])) and 100 * both >= 80 * (len(a) + len(sets[j]) - both):
                u, v = find(rows[i].doc_id), find(rows[j].doc_id)
                root[max(u, v)] = min(u, v)
    single = stages[1](spark, kept, sf).cache()
    assert keyed(single.collect()) == keyed([r for r in rows if find(r.doc_id) == r.doc_id]) and single.count() < kept.count()

    before = {r.doc_id: r.text for r in single.collect()}
    hidden = stages[2](spark, single, sf).cache()
    plain_pseudonyms = pseudonym.Pseudonyms(DEMONSTRATION_KEY.encode())
    after = hidden.collect()
    assert all(r.text == plain_pseudonyms.replace(before[r.doc_id])[0] and r.n_chars == len(r.text) for r in after)
    assert len(after) == len(before) and any(r.text != before[r.doc_id] for r in after)

    mixed = stages[3](spark, hidden, sf).cache()
    words = lambda t: len([w for w in (t or "").translate({i: 32 for i in range(9, 14)}).split(" ") if w])
    taken = {}
    for r in mixed.collect():
        taken[r.source] = taken.get(r.source, 0) + words(r.text)
    want = {r.source: r.target for r in mix.mix_report(hidden).select("source", "target").distinct().collect()}
    for source, target in want.items():
        sizes, reach = [words(r.text) for r in after if r.source == source], 1
        epochs, rest = divmod(round(target), max(1, sum(sizes)))
        for n in sizes:
            reach |= reach << n
        assert taken.get(source, 0) == epochs * sum(sizes) + max(i for i in range(rest + 1) if reach >> i & 1)
    most = mixed.groupBy("doc_id").count().agg({"count": "max"}).first()[0]
    assert most <= 3 and {r.text for r in mixed.collect()} <= {r.text for r in after}

    sp = sentencepiece.SentencePieceProcessor(model_file=PIECE_MODEL)
    sha = lambda t: hashlib.sha256(t.encode()).hexdigest()
    want = sorted((r.doc_id, len(ids), sha(",".join(map(str, ids))), sha(sp.decode(ids) if ids else "")) for r in mixed.collect() for ids in [sp.encode(r.text or "")])
    assert sorted((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in stages[4](spark, mixed, sf).collect()) == want
    assert np.isfinite(most)


def test_pipeline_keeps_foreign_columns(spark, sf):
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    odd = docs.withColumn("quality_score", F.lit("mine")).withColumn("a.b", F.lit(1)).withColumn("gone_id", F.lit(2)).withColumn("kept", F.lit(3)).withColumn("c0", F.lit(4))
    odd = odd.union(spark.createDataFrame([(None, None, None, None, None, "mine", 1, 2, 3, 4), (10**9, "", "en", None, 0, "mine", 1, 2, 3, 4)], odd.schema))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        odd = stage(spark, odd, sf)
        assert odd.columns == [*docs.columns, "quality_score", "a.b", "gone_id", "kept", "c0"]
        assert odd.count() > 0 and odd.where("quality_score <> 'mine' or `a.b` <> 1 or gone_id <> 2 or kept <> 3 or c0 <> 4").count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, odd, sf).count() == odd.count()


def test_pseudonym_key(spark, sf):
    with pytest.raises(ValueError):
        pseudonym.session_key(spark)
    with pytest.raises(ValueError):
        pseudonym.pseudonymise(spark.read.parquet(f"{sf}/documents.parquet"), "")
    spark.conf.set(pseudonym.KEY_SETTING, "other")
    assert pseudonym.session_key(spark, DEMONSTRATION_KEY) == "other"
    spark.conf.unset(pseudonym.KEY_SETTING)
