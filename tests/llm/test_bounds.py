"""What must not be cut off: short items, many seeds, wide layouts, many languages, odd ids and names."""

import random

import numpy as np
import pytest

from relq.llm import decontaminate, embeddings, language, licenses, packing, secrets, simhash, warc
from relq.llm.components import connected_components
from relq.llm.workspace import Workspace

from test_operators import BASE, components, frame, prose


def stretch(ours, theirs):
    """Best score and equal words of two texts laid on each other anyhow, by trying every shift."""
    best = 0
    for shift in range(-len(theirs) + 1, len(ours)):
        run = 0
        for k, word in enumerate(theirs):
            hit = 0 <= shift + k < len(ours) and ours[shift + k] == word
            run = max(0, run + (1 if hit else -2))
            best = max(best, run)
    return best


def test_overlaps_equal_brute_force_on_every_path(spark, monkeypatch):
    rng = random.Random(8)
    items = [(n, prose(n, 900 + n)) for n in [*range(1, 17), 24, 40]]
    rows = []
    for n, text in items:
        for k in range(4):
            words = text.split()
            for spot in rng.sample(range(n), min(k, n // 6)):
                words[spot] = "zzz"
            rows.append((len(rows), f"{prose(20, 3000 + 7 * n + k)} {' '.join(words)} {prose(9, 5000 + 7 * n + k)}"))
    rows += [(None, rows[30][1]), (3, rows[40][1])]
    want = set()
    for d, x in rows:
        for n, text in items:
            words = text.split()
            if stretch(x.split(), words) >= min(13, -(-len(words) * 7 // 10)):
                want.add((d, n))
    bench = spark.createDataFrame(items, "item_id long, text string")
    for most in (2_000_000, 0):
        monkeypatch.setattr(decontaminate, "BROADCAST_SEEDS", most)
        assert {(r.doc_id, r.item_id) for r in decontaminate.benchmark_overlaps(frame(spark, rows), bench).collect()} == want
    assert {n for _, n in want} == {n for n, _ in items}


def test_licence_blocks_count_by_words_however_they_are_set(spark):
    mit = licenses.TEMPLATES[3][1].replace(". ", ".\n")
    rows = [(1, "*" * 9_000 + "\n" + mit), (2, mit.replace(" ", " " * 60))]
    got = {(r.doc_id, r.license) for r in licenses.license_matches(frame(spark, rows), licenses.templates_frame(spark)).collect()}
    assert got == {(1, "MIT"), (2, "MIT")}


def test_every_language_is_learned(spark):
    names = [f"l{k:03d}" for k in range(401)]
    rows = [(100 * k + j, f"{chr(0x4E00 + k) * 3} {chr(0x4E00 + k)}{j}", names[k], "s", 1) for k in range(401) for j in range(12)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    model = language.train(docs, per_language=2)
    assert model.languages == names


def test_odd_ids_survive_an_archive(spark):
    html = "<p>" + "x" * 200
    rows = [("None", "u", html), ("a\r\nb: c", "v", html), (None, "w", html), ("é %0A", "x", "short"), ("a\r\nb: c", "v", html)]
    pages = spark.createDataFrame(rows, "page_id string, url string, html string")
    index, folder = warc.archive_pages(pages)
    got = sorted((str(r.page_id), r.record_type, r.refers_to) for r in warc.read_records(index, folder).collect())
    assert got == sorted([("None", "response", None), ("a\r\nb: c", "revisit", "None"), ("a\r\nb: c", "revisit", "None"), ("None", "revisit", "None"), ("é %0A", "response", None)])


def test_clashing_names_are_kept(spark):
    names = ["doc_id", "text", "n_chars", "__base", "__judged", "__mark", "__id", "__row_mark"]
    docs = spark.createDataFrame([(1, "password=abcdefghij", 19, 1, 2, 3, 4, 5), (2, "password=abcdefghij", 19, 1, 2, 3, 4, 5)], ", ".join(f"{n} {'string' if n == 'text' else 'long'}" for n in names))
    ratios = [0.0] * (secrets.ALPHABET**2)
    assert [tuple(r) for r in secrets.redact(docs, ratios).orderBy("doc_id").collect()] == [(k, "password=[SECRET]", 17, 1, 2, 3, 4, 5) for k in (1, 2)]
    assert [tuple(r) for r in simhash.keep_one_of_each(docs).collect()] == [(1, "password=abcdefghij", 19, 1, 2, 3, 4, 5)]


def test_conversations_are_packed_under_all_three_limits(spark):
    turns = spark.read.parquet("/root/testdata/sf0.001/conversations.parquet").selectExpr("conv_id * 1000 + turn AS turn_id", "text", "role = 'assistant' AS bears_loss")
    limits = packing.Limits(256, 4, 96)
    pieces = packing.pack_documents(turns, packing.vocabulary_path(), limits=limits, id_col="turn_id", loss_col="bears_loss").collect()
    totals = {}
    for p in pieces:
        n, segments, loss = totals.get(p.sequence_id, (0, 0, 0))
        totals[p.sequence_id] = (n + p.length, segments + 1, loss + p.loss_tokens)
    assert all(n <= 256 and segments <= 4 and loss <= 96 for n, segments, loss in totals.values())
    assert max(s for _, s, _ in totals.values()) == 4 and max(x for *_, x in totals.values()) > 90
    assert sum(p.length for p in pieces) == sum({p.doc_id: p.doc_tokens for p in pieces}.values())


@pytest.mark.parametrize("spread", [0.01, 0.035])
def test_recall_of_vector_pairs_on_planted_clusters(spark, spread):
    rng = np.random.default_rng(17)
    rows = [(k, rng.standard_normal(64)) for k in range(3_000)]
    for c in range(40):
        centre = rng.standard_normal(64)
        rows += [(10_000 + 100 * c + k, centre + spread * 4 * rng.standard_normal(64)) for k in range(int(rng.integers(2, 30)))]
    rows += [(90_000 + k, rows[-1][1] + 0.02 * rng.standard_normal(64)) for k in range(700)]
    vectors = spark.createDataFrame([(k, v.tolist(), 1) for k, v in rows], "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: (r.n_links, r.component_id) for r in embeddings.near_duplicate_vectors(vectors).collect()}
    unit = np.stack([v / np.linalg.norm(v) for _, v in rows])
    near = np.triu(unit @ unit.T >= 0.98, 1)
    ends = near.sum(0) + near.sum(1)
    ids = [k for k, _ in rows]
    found = sum(got[k][0] for k in ids)
    assert found >= 0.9 * ends.sum() and all(got[k][0] <= n for k, n in zip(ids, ends, strict=True))
    roots = components(len(ids), list(zip(*np.nonzero(near), strict=True)))
    same = sum(got[k][1] == min(ids[j] for j in range(len(ids)) if roots[j] == roots[i]) for i, k in enumerate(ids) if ends[i])
    assert same >= 0.9 * (ends > 0).sum()


def test_markov_ratio_finds_planted_strings_and_leaves_identifiers(spark):
    rng = random.Random(3)
    alphabet = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    words = "render widget matrix kernel window branch commit remote socket thread".split()
    planted = ["".join(rng.choices(alphabet, k=rng.randint(28, 44))) for _ in range(200)]
    plain = ["_".join(rng.choices(words, k=4)) for _ in range(100)] + ["".join(w.title() for w in rng.choices(words, k=5)) for _ in range(100)]
    rows = [(k, f"{prose(20, k)} {x} {prose(20, k + 1)}") for k, x in enumerate([*planted, *plain])]
    ratios = secrets.transition_ratios(secrets.labelled_samples(spark, frame(spark, rows)))
    found = {r.doc_id: [s.run for s in r.added] for r in secrets.secret_spans(frame(spark, rows), ratios).collect()}
    caught = sum(found[k] == [x] for k, x in enumerate(planted))
    wrong = sum(bool(found[200 + k]) for k in range(200))
    assert caught >= 180 and wrong <= 2, (caught, wrong)


def test_workspaces_can_be_deleted(spark):
    import os

    work = Workspace(spark, "t")
    connected_components(spark.createDataFrame([(1, 2)], "a long, b long"), work).count()
    folder = work.root.removeprefix("file://")
    assert os.path.isdir(folder)
    work.close()
    assert not os.path.isdir(folder) and BASE


def test_leaks_of_long_items_equal_brute_force(spark, monkeypatch):
    """Items of 13 words and more with words replaced anywhere: every pair whose best stretch is enough is found."""
    rng = random.Random(11)
    items = [(n, prose(n, 7000 + n)) for n in (13, 15, 18, 25, 43, 60, 120)]
    rows = []
    for n, text in items:
        for k in range(24):
            words, spot = text.split(), rng.randrange(3)
            while spot < n:
                words[spot] = f"zzz{k}"
                spot += rng.choice((2, 3, 4) if k % 2 else (3, 3, 4, 5))
            rows.append((len(rows), f"{prose(5, 8000 + k)} {' '.join(words)}"))
    # runs of eight equal words, three replaced between: masks of nine words with three left out found none of them
    for n, text in items[-3:]:
        rows.append((len(rows), " ".join("zzz" if k % 11 > 7 else w for k, w in enumerate(text.split()))))
    want = {(d, n) for d, x in rows for n, text in items if stretch(x.split(), text.split()) >= min(13, -(-n * 7 // 10))}
    bench = spark.createDataFrame(items, "item_id long, text string")
    for most in (2_000_000, 0):
        monkeypatch.setattr(decontaminate, "BROADCAST_SEEDS", most)
        assert {(r.doc_id, r.item_id) for r in decontaminate.benchmark_overlaps(frame(spark, rows), bench).collect()} == want
    assert {(len(rows) - 3 + k, n) for k, (n, _) in enumerate(items[-3:])} <= want
