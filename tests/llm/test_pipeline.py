import re
from collections import Counter

import corpus_pipeline
from walkfold.llm import quality, secrets
from walkfold.llm.queries import oracle_sql, queries

SF = "/root/testdata/sf0.001"


def test_stages_against_plain_versions(spark, tmp_path):
    from test_operators import brute_components, brute_hits

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels, bench = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("labels", "benchmark"))
    model = quality.train(docs, labels)
    frames = [docs]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, frames[-1], SF).write.parquet(str(tmp_path / str(k)))
        frames.append(spark.read.parquet(str(tmp_path / str(k))))
    rows = [[tuple(r) for r in f.collect()] for f in frames]
    assert all(f.columns == docs.columns for f in frames[:-1])
    text = lambda rs: [(r[0], r[1]) for r in rs]
    good = [r for r in rows[0] if model.score(quality.features([(r[1] or "").encode()]))[0] >= 0.5]
    assert Counter(rows[1]) == Counter(good)
    first = {c for _, _, c in brute_components(text(rows[1]), 5, 80)}
    assert Counter(rows[2]) == Counter(r for r in rows[1] if r[0] in first)
    bad = {r[0] for r in brute_hits(text(rows[2]), [(r.item_id, r.text) for r in bench.collect()]) if r[5]}
    assert Counter(rows[3]) == Counter(r for r in rows[2] if r[0] not in bad)
    assert {r[0] for r in rows[4]} == {r[0] for r in rows[3]}
    assert not any(re.search(r'token = "[0-9a-f]{40}"', r[1]) for r in rows[4])
    assert all(a[1] == b[1] or secrets.REDACTED in b[1] for a, b in zip(sorted(rows[3]), sorted(rows[4]), strict=True))
    mixed = Counter()
    for r in rows[5]:
        mixed[r[0]] += r[-1]
    sizes = {r[0]: len(r[1].split()) for r in rows[4]}
    assert sum(mixed.values()) <= 1.5 * sum(sizes.values()) and all(n <= 2 * sizes[i] for i, n in mixed.items())
    assert sum(mixed.values()) > 1.49 * sum(sizes.values())


def test_registered():
    assert {f"op{n}" for n in range(1, 11)} == {k.split("_")[0] for k in queries() if k.startswith("op")} and "pipeline" in queries()
    assert set(oracle_sql()) <= set(queries())
