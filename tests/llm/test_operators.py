"""Each operator against a plain version on a small fixture, with nulls, blanks, copies, odd columns and empty tables."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from relq.llm import decontaminate, embeddings, language, licenses, packing, quality, secrets, simhash, toxicity, warc
from relq.llm.components import connected_components
from relq.llm.labels import residue
from relq.llm.workspace import Workspace

RNG = random.Random(11)
WORDS = ["".join(RNG.choice("abcdefghijklmnop") for _ in range(RNG.randint(2, 7))) for _ in range(400)]
DOCS = "doc_id long, text string, lang string, source string, n_chars long, words string, fp long, start int"


def prose(n, seed):
    return " ".join(random.Random(seed).choices(WORDS, k=n))


def frame(spark, rows):
    """Documents with columns whose names clash with inner ones."""
    return spark.createDataFrame([(d, x, "en", "s", len(x) if x else None, "w", 7, 1) for d, x in rows], DOCS)


BASE = [(k, prose(60, k)) for k in range(12)]
ODD = [*BASE, (20, BASE[3][1]), (21, BASE[3][1].replace(" ", "  ")), (22, None), (23, ""), (24, " \t\n"), (25, "x"), (26, "É à ü"), (None, "no id here"), (27, "long " * 30_000), (28, prose(60, 3).upper()), (1, BASE[1][1])]


@pytest.fixture(scope="module")
def odd(spark):
    return frame(spark, ODD).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return frame(spark, [])


def components(n, pairs):
    parent = list(range(n))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return [find(x) for x in range(n)]


def fingerprint(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    runs = [b" ".join(words[k : k + 3]) for k in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(r, seed=42) for r in runs]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_simhash_matches_brute_force(spark, odd, empty):
    got = Counter((r.doc_id, r.fp & (1 << 64) - 1, r.component_id) for r in simhash.simhash_components(odd).collect())
    fps = [fingerprint(x) for _, x in ODD]
    near = [(i, j) for i in range(len(fps)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 2]
    roots = components(len(fps), near)
    least = {r: min((ODD[i][0] for i in range(len(ODD)) if roots[i] == r and ODD[i][0] is not None), default=None) for r in set(roots)}
    assert got == Counter((ODD[i][0], fps[i], least[roots[i]]) for i in range(len(ODD)))
    assert simhash.simhash_components(empty).count() == 0


def test_vantage_tree_finds_all_pairs_between_shards():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 1 << 63, 400, dtype=np.uint64)
    flips = np.uint64(1) << rng.integers(0, 64, 400).astype(np.uint64)
    points = np.unique(np.concatenate([base, base ^ flips, base ^ flips ^ np.uint64(8)]))
    tree = simhash.VantageTree(points[::3], 10)
    leaf, index, home = tree.route(points, 2)
    assert tree.leaves > 8 and sorted(index[home]) == list(range(len(points)))
    found = set()
    for k in range(tree.leaves):
        q, h = index[leaf == k], index[(leaf == k) & home]
        for i, j in simhash._close(points[q], points[h], 2):
            found |= {(min(a, b), max(a, b)) for a, b in zip(q[i], h[j]) if a != b}
    want = {(i, j) for i in range(len(points)) for j in range(i + 1, len(points)) if int(points[i] ^ points[j]).bit_count() <= 2}
    assert found == want and want


def test_components_of_long_chains(spark):
    chain = [(k, k + 1) for k in range(300)] + [(1000, 1001), (1001, 1000), (5, 5)]
    roots = connected_components(spark.createDataFrame(chain, "a long, b long"), Workspace(spark, "t"))
    got = {r.node: r.root for r in roots.collect()}
    assert all(got[k] == 0 for k in range(301)) and got[1001] == 1000 and got[1000] == 1000
    assert connected_components(spark.createDataFrame([], "a long, b long"), Workspace(spark, "t")).count() == 0


def test_equal_fingerprints_alone_make_no_near_duplicates(spark):
    common = "one two three four five six seven " * 400
    texts = [common + " ".join(f"{who}{k}" for k in range(12)) for who in ("ada", "bob")]
    assert len({simhash.majority_bits(simhash.shingle_hashes(t.encode(), 5)) for t in texts}) == 1
    rows = spark.createDataFrame([(k, t, "en", "web", len(t)) for k, t in enumerate([*texts, texts[0]])], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in simhash.keep_one_of_each(rows).collect()) == [0, 1]


def jaccard(a, b):
    a, b = ({tuple(w[k : k + 5]) for k in range(len(w) - 4)} for w in (a.split(), b.split()))
    return len(a & b) / len(a | b)


def test_copies_are_found_among_texts_that_share_a_passage(spark):
    passage, texts = prose(600, 500), []
    for k in range(60):
        text = f"{passage} {prose(100, 600 + k)}"
        words = text.split()
        words[620:680] = prose(60, 700 + k).split()
        texts += [text, " ".join(words)]
    assert all(jaccard(texts[k], texts[k + 1]) >= 0.8 > max(jaccard(texts[k], x) for x in texts[k + 2 :]) for k in (0, 50, 100))
    kept = simhash.keep_one_of_each(frame(spark, list(enumerate(texts))))
    assert sorted(r.doc_id for r in kept.collect()) == list(range(0, 120, 2))


def test_copies_are_found_among_equal_fingerprints(spark, monkeypatch):
    monkeypatch.setattr(simhash, "band_keys", lambda hashes: np.random.default_rng(int(hashes.sum() % 2**32)).integers(0, 1 << 63, simhash.BANDS, dtype=np.uint64))
    common = "one two three four five six seven " * 400
    texts = [common + " ".join(f"{who}{k}" for k in range(60)) for who in ("ada", "bob", "cyd", "dan")]
    rows = [(2 * k + j, t + " end" * j) for k, t in enumerate(texts) for j in (0, 1)]
    assert len({simhash.majority_bits(simhash.shingle_hashes(t.encode(), 5)) for _, t in rows}) == 1
    groups, _ = simhash.near_duplicate_texts(frame(spark, rows))
    roots = {r.first_id: r.root for r in groups.collect()}
    assert len(roots) == 8 and len(set(roots.values())) == 4 and all(roots[k] == roots[k + 1] for k in (0, 2, 4, 6))


def test_pairs_within_two_bits(spark):
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, 30, dtype=np.uint64)
    points = np.unique(np.concatenate([base, *[base ^ np.uint64((1 << k) | (1 << (k + 5))) for k in range(0, 12, 3)], *[base ^ np.uint64(1 << k) for k in (0, 7)]])).view(np.int64)
    teams = [-1 if k % 3 else k % 2 for k in range(len(points))]
    rows = spark.createDataFrame([(int(p), t) for p, t in zip(points, teams, strict=True)], "fp long, team long")
    got = sorted((r.a, r.b) for r in simhash.links_within(rows, 2, Workspace(spark, "t"), pairs=True).collect())
    far = np.bitwise_count(points[:, None] ^ points)
    n = len(points)
    assert got == sorted((int(points[i]), int(points[j])) for i in range(n) for j in range(n) if points[i] < points[j] and far[i, j] <= 2 and (teams[i] != teams[j] or teams[i] < 0)) and len(got) > 100


def test_shared_counts_in_sets():
    rng = np.random.default_rng(3)
    sets = [np.unique(np.concatenate([rng.integers(0, 60, 20), np.arange(100, 130)])) for _ in range(9)] + [np.empty(0, int)]
    got = simhash.shared_counts(np.repeat(np.arange(10), [len(x) for x in sets]), np.concatenate(sets), 10)
    assert all(got[i, j] == len(np.intersect1d(sets[i], sets[j])) for i in range(10) for j in range(10) if i != j)


def test_one_of_each_near_duplicate_group_stays(spark, odd, empty):
    text = prose(300, 99)
    near = text.replace(text.split()[150], "changed", 1)
    far = prose(300, 98)
    rows = [(50, text), (51, near), (52, far), (53, text), (53, text)]
    kept = simhash.keep_one_of_each(frame(spark, [*ODD, *rows]))
    ids = sorted(r.doc_id for r in kept.collect() if r.doc_id is not None)
    assert [i for i in ids if i >= 50] == [50, 52]
    assert ids == sorted(set(ids)) and {0, 1, 2, 3} <= set(ids) and 20 not in ids
    assert sum(i in ids for i in (22, 23, 24)) == 1
    assert kept.columns == odd.columns and simhash.keep_one_of_each(empty).count() == 0


def test_packing_is_an_exact_partition(spark, odd, empty):
    from tokenizers import Tokenizer

    path = packing.vocabulary_path()
    encoder = Tokenizer.from_file(path)
    nasty = [(40, "it's O'Neil's #tag 12345 <|endoftext|> ﬁne İstanbul ½ a\x1cb é"), (41, "日本語 text, mixed. words!! %%%")]
    rows = [r for r in [*ODD, *nasty] if r[0] != 1]
    pieces = packing.pack_documents(frame(spark, rows), path).collect()
    want = {d: np.array([*encoder.encode(x or "", add_special_tokens=False).ids, 1], "<u4") for d, x in rows}
    at, spots = Counter(), {}
    for p in sorted(pieces, key=lambda p: (p.doc_id if p.doc_id is not None else -1, p.start)):
        ids = want[p.doc_id]
        assert p.start == at[p.doc_id] and p.doc_tokens == len(ids)
        assert p.ids_crc32 == zlib.crc32(ids[p.start : p.start + p.length].tobytes()) and p.ids == ids[p.start : p.start + p.length].tolist()
        at[p.doc_id] += p.length
        spots.setdefault(p.sequence_id, []).append((p.offset, p.length))
    assert at == {d: len(x) for d, x in want.items()}
    for parts in spots.values():
        end = 0
        for offset, length in sorted(parts):
            assert offset == end
            end += length
        assert end == 2048 or end & (end - 1) == 0
    assert packing.pack_documents(empty, path).count() == 0


def test_packing_keeps_all_limits():
    limits = packing.Limits(64, 3, 40)
    packer, rng = packing.DotProductPacker(limits, pool=20), random.Random(2)
    pieces = [packing.Piece(k, 0, rng.randint(1, 150), rng.random() < 0.5) for k in range(300)]
    total = sum(p.stop for p in pieces)
    out = [*packer.add(pieces), *packer.close()]
    assert sum(p.stop - p.start for s in out for p in s) == total
    for s in out:
        assert len(s) <= 3 and sum(p.stop - p.start for p in s) <= 64 and sum((p.stop - p.start) * p.loss for p in s) <= 40


def test_warc_round_trip(spark):
    html = "<p>" + "x" * 200 + "é</p>"
    rows = [(5, "http://a/b c\n", html), (2, None, html), (9, "http://c", html), (3, "http://d", "short"), (4, "http://e", "short"), (7, "http://f", None), (None, "http://g", html), (8, "u", "y" * 300_000)]
    pages = spark.createDataFrame([(*r, 1) for r in rows], "page_id long, url string, html string, offset int")
    index, folder = warc.archive_pages(pages)
    got = {r.page_id: r for r in warc.read_records(index, folder).collect()}
    for page, _, body in rows:
        raw = (body or "").encode()
        r = got[page]
        revisits = body == html and page != 2
        assert (r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) == (len(raw), hashlib.sha256(raw).hexdigest(), "revisit" if revisits else "response", 2 if revisits else None)
        assert (r.payload is None) if revisits else (bytes(r.payload) == raw)
    some = index.where("page_id in (3, 8)")
    assert sorted(r.page_id for r in warc.read_records(some, folder).collect()) == [3, 8]
    assert warc.archive_pages(pages.limit(0))[0].count() == 0


def test_ranges_are_joined_up_to_gap_and_size():
    ranges = [(0, 10), (12, 5), (100, 5), (106, 50)]
    assert list(warc.coalesce_ranges(ranges, gap=5, most=60)) == [(0, 2, 0, 17), (2, 4, 100, 156)]
    assert [x[:2] for x in warc.coalesce_ranges(ranges, gap=0, most=60)] == [(0, 1), (1, 2), (2, 3), (3, 4)]


ASSIGN = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)


def spans_of(text):
    out = [(m.start(), 0, m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    out += [(m.start(), 1, m.end(), "access") for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 16]
    out += [(m.start(), 2, m.end(), "hex") for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 32]
    return sorted(out)


def test_secret_spans_match_plain_patterns(spark, odd, empty):
    digest = hashlib.sha256(b"q").hexdigest()
    texts = [
        f'é𝄞 token = "{digest}" and AKIA{"Q" * 16}', "secret=token:abcdefghij", "password:short pASSWORD : longvalue123", "api_key==abcdefgh apikey='zzzzzzzzz'", digest * 3, "AKIAQ AKIA" + "7" * 12,
        "token=" * 50 + "abcdefgh1", "passwd\t=abcdefghi secretsecret=12345678", "see q7Zt9LwX2bVn4KpR8sDf1GhJ5mYc3TeA here", None, "",
    ]
    rows = [(100 + k, x) for k, x in enumerate(texts)]
    ratios = secrets.transition_ratios(secrets.labelled_samples(spark, odd))
    found = {r.doc_id: r for r in secrets.secret_spans(frame(spark, [*rows, *[r for r in ODD if r[0] not in (1, None)]]), ratios).collect()}
    for d, x in rows:
        assert [(s.start, s.order, s.stop, s.kind) for s in found[d].base] == spans_of(x or ""), x
    assert [s.run for s in found[108].added] == ["q7Zt9LwX2bVn4KpR8sDf1GhJ5mYc3TeA"]
    assert not any(found[d].added for d, _ in ODD if d not in (1, None))
    clean = {r.doc_id: r for r in secrets.redact(frame(spark, rows), ratios).collect()}
    assert clean[100].text == 'é𝄞 token = "[SECRET]" and [SECRET]' and clean[100].n_chars == len(clean[100].text)
    assert clean[109].text is None and clean[101].text == texts[1]
    assert secrets.secret_spans(empty, ratios).count() == 0 and secrets.transition_ratios(secrets.labelled_samples(spark).limit(0))[0] == 0


def test_benchmark_overlaps(spark, odd, empty):
    items = [(1, prose(40, 500)), (2, prose(20, 501)), (3, "six words are in this item"), (4, "too short"), (5, None), (6, prose(40, 500))]
    swapped = items[0][1].split()
    for k in (5, 14, 23, 33):
        swapped[k] = "zzz"
    rows = [(60, f"{prose(30, 1)} {items[0][1]} {prose(30, 2)}"), (61, " ".join(swapped).upper()), (62, prose(50, 9) + " " + " ".join(items[0][1].split()[8:24])), (63, "Six words, are in THIS item!"), (64, " ".join(items[0][1].split()[:8])), (65, items[1][1]), (66, "too short")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontaminate.benchmark_overlaps(frame(spark, [*ODD, *rows]), bench).collect()}
    assert got == {(d, i) for d in (60, 61, 62) for i in (1, 6)} | {(63, 3), (65, 2), (66, 4)}
    kept = decontaminate.drop_contaminated(frame(spark, rows), bench)
    assert sorted(r.doc_id for r in kept.collect()) == [64] and kept.columns == odd.columns
    assert decontaminate.benchmark_overlaps(empty, bench).count() == 0 and decontaminate.benchmark_overlaps(odd, bench.limit(0)).count() == 0


def test_license_matches_equal_brute_force(spark, odd, empty):
    def grams(x):
        w = re.findall(r"[a-z0-9\x80-\U0010ffff]+", x.lower())
        return Counter(zip(w, w[1:]))

    mit = licenses.TEMPLATES[3][1]
    rows = [(70, f"{prose(30, 1)}\nReleased under the MIT License."), (71, "LICENSED under the apache license, version 2.0!!"), (72, "Licensed under CC BY-NC 4.0\nReleased under the MIT License."), (73, mit.replace(". ", ".\n")), (74, "Permission is hereby granted"), (75, "the mit license"), (None, "Licensed under CC BY 4.0")]
    templates = licenses.templates_frame(spark)
    got = {(r.doc_id, r.license, round(r.dice, 6)) for r in licenses.license_matches(frame(spark, [*ODD, *rows]), templates).collect()}
    want = {}
    for d, x in rows:
        for segment in [*x.split("\n"), x]:
            a, best = grams(segment), None
            for number, (name, text) in enumerate(licenses.TEMPLATES):
                b = grams(text)
                dice = 2 * sum((a & b).values()) / max(1, a.total() + b.total())
                if dice >= 0.8 and (best is None or dice > best[0]):
                    best = (dice, name)
            if best:
                want[d, best[1]] = max(want.get((d, best[1]), 0), round(best[0], 6))
    assert got == {(*k, v) for k, v in want.items()} and len(got) >= 6
    assert licenses.license_matches(empty, templates).count() == 0


def test_license_texts_with_blank_lines(spark):
    def grams(x):
        w = re.findall(r"[a-z0-9\x80-\U0010ffff]+", x.lower())
        return Counter(zip(w, w[1:]))

    mit = licenses.TEMPLATES[3][1]
    for cut in (" The above copyright", " THE SOFTWARE IS"):
        mit = mit.replace(cut, "\n\n" + cut.strip())
    rows = [(80, mit), (81, f"Copyright (c) 2020 Ada\n\n{mit}\n\n{prose(50, 4)}"), (82, f"{prose(90, 5)}\n\n{mit}".replace("\n\n", "\r\n \r\n")), (83, mit.split("\n\n")[0] + "\n\n" + prose(200, 6)), (None, mit)]
    got = {r.doc_id: (r.license, round(r.dice, 6), r.level) for r in licenses.license_matches(frame(spark, rows), licenses.templates_frame(spark)).collect()}
    want = {}
    for d, x in rows:
        blocks, t = re.split(r"\n\s*\n", x), grams(licenses.TEMPLATES[3][1])
        best = max(2 * (a & t).total() / (a.total() + t.total()) for i in range(len(blocks)) for j in range(i + 1, len(blocks) + 1) for a in [grams("\n".join(blocks[i:j]))])
        if best >= 0.8:
            want[d] = ("MIT", round(best, 6), "run")
    assert got == want and set(want) == {80, 81, 82, None}


def test_vector_links_match_brute_force(spark):
    rng = np.random.default_rng(3)
    near = rng.standard_normal(16)
    rows = [(k, rng.standard_normal(16).tolist(), 1) for k in range(60)]
    rows += [(100 + k, (near + 0.02 * rng.standard_normal(16)).tolist(), 1) for k in range(40)] + [(200, near.tolist(), 2), (201, (3 * near).tolist(), 2), (202, near.tolist(), None)]
    rows += [(300 + k, rows[0][1], 1) for k in range(5)] + [(400, None, 1), (401, [0.0] * 16, 1), (402, [float("nan")] * 16, 1), (403, [None, 1.0], 1), (404, [], 1), (405, [float("inf")] * 16, 1), (406, [1.0, 0.0], 1), (407, [2.0, 0.0], 1)]
    vectors = spark.createDataFrame([(*r, "x") for r in rows], "vec_id long, embedding array<double>, label int, rid string")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embeddings.near_duplicate_vectors(vectors).collect()}
    ok = [k for k, (_, v, l) in enumerate(rows) if l is not None and v and None not in v and np.isfinite(v).all() and any(v)]
    unit = {k: np.array(rows[k][1]) / np.linalg.norm(rows[k][1]) for k in ok}
    pairs = [(i, j) for i in ok for j in ok if j < i and rows[i][2] == rows[j][2] and len(unit[i]) == len(unit[j]) and unit[i] @ unit[j] >= 0.98]
    degree, roots = Counter(x for p in pairs for x in p), components(len(rows), pairs)
    for k, (v, _, _) in enumerate(rows):
        root = min(rows[j][0] for j in range(len(rows)) if roots[j] == roots[k])
        assert got[v] == (degree[k], root, v == root)
    assert embeddings.near_duplicate_vectors(vectors.limit(0)).count() == 0


def labelled(spark, n):
    bad, rows, marks = ["grobnak", "vilquist", "snerdle"], [], []
    for k in range(n):
        words = prose(40, 1000 + k).split()
        toxic, poor = k % 4 == 0, k % 3 == 0
        if toxic:
            for j in (3, 17, 29):
                words[j] = bad[(k + j) % 3]
        text = " ".join(w + "###" if poor else w for w in words) if poor and not toxic else " ".join(words)
        rows.append((k, text))
        marks.append((k, int(not (poor and not toxic)), int(toxic)))
    return frame(spark, rows), spark.createDataFrame([*marks, (None, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")


def test_residue_is_the_crc_of_the_id_as_text(spark):
    got = {r.doc_id: r.k for r in spark.range(50).toDF("doc_id").select("doc_id", residue(pytest.importorskip("pyspark.sql.functions").col("doc_id"), 3).alias("k")).collect()}
    assert got == {k: zlib.crc32(str(k).encode()) % 3 for k in range(50)}


def test_toxicity_on_held_out_documents(spark, odd, empty):
    docs, labels = labelled(spark, 400)
    model = toxicity.train(docs, labels)
    scores = {r.doc_id: r.score for r in toxicity.score_documents(docs, model).collect()}
    held = [k for k in scores if zlib.crc32(str(k).encode()) % 3 == 1]
    assert len(held) > 100 and all((scores[k] >= 0.7) == (k % 4 == 0) for k in held)
    rest = [r.score for r in toxicity.score_documents(odd, model).collect()]
    assert len(rest) == len(ODD) and all(0 <= x < 0.7 for x in rest)
    assert toxicity.score_documents(empty, model).count() == 0
    assert toxicity.keep_clean(docs, model).count() == 300
    blank = toxicity.train(empty, labels.limit(0))
    assert blank.scores(pa.array(["you idiot", None]))[0] > blank.scores(pa.array([None]))[0]


def test_clause_machine_tells_kinds_apart():
    machine = toxicity.clause_machine()

    def kinds(symbols):
        state, out = machine.start, []
        for s in symbols.split():
            state, kind = machine.step(state, s)
            out.append(kind)
        return out

    assert kinds("target other insult")[-1] == "insult+target"
    assert kinds("negation insult")[-1] == "insult-negated"
    assert kinds("target report other threat")[-1] == "threat-reported"
    assert kinds("insult")[-1] == "insult"
    assert kinds("negation other other other insult")[-1] == "insult"
    grammar = toxicity.Grammar({})
    assert grammar.features("you are a moron").sum() > 0 and not grammar.features("a fine day").any()
    assert grammar.features("she said. you idiot")[toxicity.KINDS.index("insult+target")] > 0


def test_matches_next_to_any_mark_count():
    grammar = toxicity.Grammar({"grobn*": 3.0, "vilquist": 2.5})
    for insult in ("idiot", "vilquist", "grobnakish"):
        for text in ("'{}'", "{}—you", "¡{}!", "{}’", "‘{}’", "a–{}–b", "¿{}?", "a·{}"):
            assert grammar.features(text.format(insult)).any(), (text, insult)
    assert not grammar.features("a fine — 'day' grob").any()


def test_quality_on_held_out_documents(spark, odd, empty):
    docs, labels = labelled(spark, 400)
    scores = {r.doc_id: r.score for r in quality.quality_scores(docs, labels).collect()}
    held = [k for k in scores if zlib.crc32(str(k).encode()) % 5 == 0]
    right = sum((scores[k] >= 0.3) == (not (k % 3 == 0 and k % 4)) for k in held)
    assert right / len(held) > 0.95 and all(0 <= x <= 1 for x in scores.values())
    assert quality.quality_scores(odd, labels).count() == len(ODD) and quality.quality_scores(empty, labels).count() == 0


def test_isotonic_and_normal_equations(spark):
    levels = quality.isotonic(np.array([1, 1, 0, 2, 1]), np.array([1, 0, 0, 2, 0]))
    assert (np.diff(levels) >= 0).all() and np.allclose(levels[:2], 0.5) and np.allclose(levels[-2:], 2 / 3)
    x = np.random.default_rng(0).random((50, len(quality.STATISTICS)))
    features = quality.FourierFeatures(x.mean(0), x.std(0))
    rows = spark.createDataFrame([(r.tolist(), k % 2) for k, r in enumerate(x)], "x array<double>, label int").repartition(3)
    gram, target, n = quality.normal_equations(rows, features)
    z, y = features(x), np.arange(50) % 2
    assert n == 50 and np.allclose(gram, z.T @ z, atol=1e-6) and np.allclose(target, z.T @ y, atol=1e-6)


def test_language_on_held_out_documents(spark, empty):
    rng, rows = random.Random(4), []
    letters = {"aa": "abcde", "bb": "fghij", "cc": "éàüöè"}
    for k in range(240):
        name = ("aa", "bb", "cc")[k % 3]
        rows.append((k, " ".join("".join(rng.choices(letters[name], k=5)) for _ in range(20)), name))
    odd_rows = [(900, None, "aa"), (901, "123 !?", "aa"), (902, "", None), (903, "abcde " * 40_000, None)]
    docs = spark.createDataFrame([*rows, *odd_rows], "doc_id long, text string, lang string")
    model = language.train(docs)
    got = {r.doc_id: (r.lang_pred, r.score) for r in language.identify(docs, model).collect()}
    assert all(got[d][0] == name for d, _, name in rows if zlib.crc32(str(d).encode()) % 3 == 1)
    assert got[900] == got[901] == got[902] == ("und", 0.0) and got[903][0] == "aa"
    assert all(0 <= s <= 1 for _, s in got.values())
    assert language.identify(empty, model).count() == 0 and language.train(empty).languages == []


def test_kernel_is_the_cosine_of_presence():
    x = language.presence(["abcabc", "xyz", "", "ABCABC"])
    k = language.kernel(x, x)
    assert np.allclose(np.diag(k)[[0, 1]], 1) and k[0, 3] == 1 and k[2].sum() == 0 and k[0, 1] < 0.3
