"""The pipeline, stage by stage on what the stage before kept, against brute force."""

import random

import corpus_pipeline
from diversify.llm import mixing, quality

from test_documents import TOKEN, components, corpus, fingerprint, lower


def test_stages_against_brute_force(spark, tables):
    rng = random.Random(9)
    good = [(i, t.replace("\n", " ").capitalize() + ".", "en", s, 1) for i, t, _, s, _ in corpus(48)]
    bad = [(100 + i, "\n".join("BUY!! NOW$$$ FREE***" for _ in range(8)), "en", "s0", 1) for i in range(20)]
    item = " ".join(f"q{i}" for i in range(14))
    leaked = [(200, "Some plain words before. " + item + " and some after it.", "en", "s1", 1), (201, item[:20], "en", "s1", 1)]
    private = [(300, "Write to someone@mail.example.com about the river and the house today.", "en", "s2", 1)]
    docs = good + bad + leaked + private
    labels = [(r[0], int(r[0] < 100), 0) for r in good + bad if rng.random() < 0.8]
    d = tables(documents=docs, labels=labels, benchmark=[(1, item)])

    # The run writes and reads between stages; here each stage's rows are looked at.
    now = spark.read.parquet(f"{d}/documents.parquet")
    columns = now.columns
    kept = {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, now, d)
        out.write.parquet(f"{d}/stage{k}")
        now = spark.read.parquet(f"{d}/stage{k}")
        kept[name] = {r.doc_id: r.text for r in now.collect()}
        if k < len(corpus_pipeline.STAGES) - 1:
            assert set(out.columns) == set(columns)
    text = {r[0]: r[1] for r in docs}
    field = quality.train(spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet"))
    first = kept["quality classifier"]
    assert set(first) == {i for i, t in text.items() if field.scores([t.encode()])[0] >= 0.5}
    assert not set(first) & {r[0] for r in bad} and len(set(first) & {r[0] for r in good}) >= 0.9 * len(good)
    second = kept["SimHash near-dedup"]
    assert set(second) == set(components({i: fingerprint(t) for i, t in first.items()}).values())
    w = TOKEN.findall(lower(item))
    windows = {tuple(w[p : p + 10]) for p in range(len(w) - 9)}
    words = {i: TOKEN.findall(lower(t)) for i, t in second.items()}
    third = kept["benchmark decontamination"]
    assert set(third) == {i for i, x in words.items() if not any(tuple(x[p : p + 10]) in windows for p in range(len(x)))}
    assert 200 not in third
    fourth = kept["PII"]
    assert set(fourth) == set(third) and all("@" not in t for t in fourth.values())
    if 300 in fourth:
        assert fourth[300] == "Write to [EMAIL] about the river and the house today."
    source = {r[0]: r[3] for r in docs}
    sizes = {}
    for i, t in fourth.items():
        sizes[source[i]] = sizes.get(source[i], 0) + len(t.split())
    want = mixing.targets([sizes[s] for s in sorted(sizes)])
    taken = {}
    for r in now.collect():
        taken[r.source] = taken.get(r.source, 0) + r.words
    assert all(abs(taken.get(s, 0) - t) <= 1 for s, t in zip(sorted(sizes), want, strict=True))


def test_run_returns_the_mix(spark, tables):
    d = tables(documents=corpus(20), labels=[(i, 1, 0) for i in range(20)])
    found = corpus_pipeline.run(spark, d)
    assert {"doc_id", "text", "pass", "shard", "words"} <= set(found.columns) and found.count() > 0


def test_run_on_empty_tables(spark, tables):
    assert corpus_pipeline.run(spark, tables()).collect() == []
