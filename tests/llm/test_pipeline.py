import importlib

import pytest

from relq.llm import registry

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def steps(spark):
    pipeline = importlib.import_module("corpus_pipeline")
    docs, out = spark.read.parquet("/root/testdata/sf0.001/documents.parquet"), []
    for name, stage in pipeline.STAGES:
        after = stage(spark, docs, "/root/testdata/sf0.001").persist()
        out.append((name, docs, after))
        docs = after
    return out


def test_stages_keep_columns_and_shrink(steps):
    assert [n for n, *_ in steps] == ["toxicity", "near-duplicates", "decontamination", "secrets", "packing"]
    for _, before, after in steps[:-1]:
        assert after.columns == COLUMNS and 0 < after.count() <= before.count()
    _, before, pieces = steps[-1]
    assert {r.doc_id for r in pieces.select("doc_id").distinct().collect()} == {r.doc_id for r in before.select("doc_id").collect()}


def test_near_duplicate_stage_against_brute_force(steps):
    before = {r.doc_id: r.text for r in steps[1][1].collect()}
    after = {r.doc_id for r in steps[1][2].collect()}
    sets = {}
    for d, x in before.items():
        w = (x or "").encode().lower().split()
        sets[d] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
    parent = {d: d for d in before}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(before)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            s = len(sets[a] & sets[b])
            if s >= 0.8 * (len(sets[a]) + len(sets[b]) - s):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    assert after == {find(d) for d in ids}


def test_all_ten_operators_are_registered():
    assert {int(n[2:].split("_")[0]) for n in registry.QUERIES} == set(range(1, 11))
