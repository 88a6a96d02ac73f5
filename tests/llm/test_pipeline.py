"""The whole pipeline on planted rows, each stage against a plain version on its own input."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from modelsort.llm import decontaminate, mixing, quality, simhash, toxicity

SF = "/root/testdata/sf0.01"
SHAPE = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def planted(spark, tmp_path_factory):
    """The given documents with planted ones, and a folder of all tables."""
    folder = tmp_path_factory.mktemp("planted")
    given = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars").collect()
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").select("item_id", "text").collect()]
    toxic = {r["doc_id"] for r in spark.read.parquet(f"{SF}/labels.parquet").where("toxic = 1").collect()}
    good = {r["doc_id"] for r in spark.read.parquet(f"{SF}/labels.parquet").where("toxic = 0 and quality = 1").collect()}
    rnd = random.Random(9)
    clean = [r for r in given if r["doc_id"] in good and r["lang"] == "en" and 300 < len(r["text"]) < 3000][:6]
    bad = [r for r in given if r["doc_id"] in toxic and r["lang"] == "en"][:5]
    more = [(10**6 + i, r["text"], "en", "copy", 0) for i, r in enumerate(clean)]
    more += [(10**6 + 100 + i, r["text"], "en", "toxic", 0) for i, r in enumerate(bad)]
    more += [(10**6 + 200 + i, items[i][1], "en", "benchmark", 0) for i in range(5)]
    more += [(10**6 + 300, None, None, "odd", None), (10**6 + 301, "", "en", "odd", 0), (None, clean[0]["text"], "en", "odd", 0), (10**6 + 302, clean[1]["text"] + " " + " ".join(rnd.choice(clean[2]["text"].split()) for _ in range(400)), "en", "fresh", 0)]
    spark.createDataFrame([tuple(r) for r in given] + more, SHAPE).repartition(6).write.parquet(f"{folder}/documents.parquet")
    for name in ("labels", "benchmark"):
        spark.read.parquet(f"{SF}/{name}.parquet").write.parquet(f"{folder}/{name}.parquet")
    return str(folder), items, [r["doc_id"] for r in clean]


def test_stages_and_run_against_plain_versions(spark, planted):
    folder, items, clean = planted
    read = lambda name: spark.read.parquet(f"{folder}/{name}.parquet")
    docs = read("documents").cache()
    rows = lambda df: sorted((tuple(r) for r in df.select("doc_id", "text").collect()), key=str)
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["toxicity", "quality classifier", "SimHash near-dedup", "benchmark decontamination", "mixing sources to target weights"]

    # Toxicity and quality: the rows whose own score, one text at a time, is on the right side.
    mild = corpus_pipeline.drop_toxic(spark, docs, folder).cache()
    model = toxicity.train(docs, read("labels"))
    import pyarrow as pa

    score = {t: toxicity.score_array(model, pa.array([t], pa.string()))[0]["score"].as_py() for t in {r["text"] for r in docs.collect()}}
    assert rows(mild) == rows(docs.where(F.col("text").isNull() | F.col("text").isin([t for t, s in score.items() if t is not None and s < 0.5]))) and score[None] < 0.5
    assert mild.columns == docs.columns and mild.where("source = 'toxic'").count() == 0
    fine = corpus_pipeline.keep_quality(spark, mild, folder).cache()
    net = quality.train(mild, read("labels"))
    score = {t: quality.score_array(net, pa.array([t], pa.string()))[0]["score"].as_py() for t in {r["text"] for r in mild.collect()}}
    assert rows(fine) == rows(mild.where(F.col("text").isin([t for t, s in score.items() if t is not None and s >= quality.THRESHOLD]) | (F.col("text").isNull() & F.lit(score[None] >= quality.THRESHOLD))))

    # Near-duplicates: all pairs of fingerprints.
    one = corpus_pipeline.near_dedup(spark, fine, folder).cache()
    held = [(r["doc_id"], r["text"]) for r in fine.collect()]
    prints = simhash.fingerprint_array(pa.array([t for _, t in held], pa.string()))
    named = [i for i, (d, _) in enumerate(held) if d is not None]
    label = {i: i for i in named}
    for i in named:
        for j in np.flatnonzero(np.bitwise_count(prints ^ prints[i]) <= 3).tolist():
            if j in label and label[j] != label[i]:
                a, b = label[i], label[j]
                label = {k: (a if v == b else v) for k, v in label.items()}
    lead = {}
    for i in named:
        lead[label[i]] = min(lead.get(label[i], i), i, key=lambda k: held[k][0])
    assert rows(one) == sorted([held[i] for i in lead.values()] + [h for h in held if h[0] is None], key=str)
    assert one.where("source = 'copy'").count() == 0

    # Decontamination: every window of every item looked for in every text.
    apart = corpus_pipeline.drop_contaminated(spark, one, folder).cache()
    own = [(str(i), t) for i, t in items if i is not None and t is not None]
    windows = {tuple(w[p : p + min(13, len(w))]) for _, t in own for w in [decontaminate.plain_words(t)] for p in range(max(1, len(w) - 12)) if w}
    sizes = {len(w) for w in windows}

    def dirty(text):
        words = decontaminate.plain_words(text)
        hit = {q + k for n in sizes for q in range(len(words) - n + 1) if tuple(words[q : q + n]) in windows for k in range(n)}
        return bool(hit) and 20 * len(hit) >= len(words)

    assert rows(apart) == sorted((h for h in ((r["doc_id"], r["text"]) for r in one.collect()) if not dirty(h[1])), key=str)
    assert apart.where("source = 'benchmark'").count() == 0

    # Mixing: rates meet equal targets for the documents' own memberships.
    mixed = corpus_pipeline.mix_languages(spark, apart, folder).cache()
    _, fit, names = mixing.mix(apart, corpus_pipeline.labelled_languages(apart, read("labels")))
    assert fit.converged and fit.totals == pytest.approx(fit.targets, rel=1e-6)
    assert mixed.columns == [*docs.columns, "rate", "copies"] and mixed.where("rate <= 0").count() == 0

    # The run is the stages one after another; clean documents and those without id come through.
    result = {(r["doc_id"], r["text"]): r["rate"] for r in corpus_pipeline.run(spark, folder).collect()}
    assert result.keys() == {(r["doc_id"], r["text"]) for r in mixed.collect()}
    assert result == {(r["doc_id"], r["text"]): pytest.approx(r["rate"], rel=1e-6) for r in mixed.collect()}
    kept = {i for i, _ in result}
    assert None in kept and sum(i in kept for i in clean) >= 5 and 10**6 + 302 in kept


def test_clashing_columns(spark, planted):
    folder = planted[0]
    docs = spark.read.parquet(f"{folder}/documents.parquet").limit(150)
    for name in ("rate", "copies", "__id", "__match", "__keep", "word", "domain"):
        docs = docs.withColumn(name, F.lit("mine"))
    for _, stage in corpus_pipeline.STAGES[2:4]:
        out = stage(spark, docs, folder)
        assert out.columns == docs.columns and {r[0] for r in out.select("__keep").collect()} == {"mine"}
    mixed = corpus_pipeline.mix_languages(spark, docs, folder)
    assert mixed.columns == [*(c for c in docs.columns if c not in ("rate", "copies")), "rate", "copies"]
    assert mixed.where("rate > 0").count() == mixed.count() > 0


def test_empty_documents(spark, planted):
    folder = planted[0]
    docs = spark.read.parquet(f"{folder}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, folder).count() == 0
