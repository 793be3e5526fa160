"""Benchmark passages in documents, found by spaced seeds and verified on their diagonal.

A seed hashes the words of a window that a fixed mask selects and ignores the
others, so a replaced word spoils only the seeds that select it. A seed found
in a document and in a benchmark item fixes how the two texts would lie on each
other; the words there are then compared, and the best stretch is scored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Masks, with the least and most words of the items they serve; all begin with as many selected words as their seeds' lead.
#: They miss no leak. Runs of equal words between replaced words that avoid the first three masks have at most three words,
#: and two neighbouring runs at most four, so a stretch of r replaced words scores at most 2 (r odd) or 3 (r even), and an
#: item of five words or more leaks at 4 or more. Shorter items leak only by a run of three, two or one words.
MASKS = (("1111", 5, None), ("110111", 5, None), ("111011", 5, None), ("111", 3, 4), ("11", 2, 2), ("1", 1, 1))
SPAN = max(len(m) for m, *_ in MASKS)
#: A stretch scores 1 for an equal word and -2 for a replaced one.
MISMATCH, FULL_SCORE, SHARE = 2, 13, 0.7
#: Seeds of the benchmark that may be broadcast; more are joined by a shuffle.
BROADCAST_SEEDS = 2_000_000


def word_hashes(text: Column) -> Column:
    """XXH64 of each run of letters and digits, lower-cased, in order."""
    words = F.filter(F.split(F.lower(F.coalesce(text.cast("string"), F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    return F.transform(words, lambda w: F.xxhash64(w))


def seed(words: Column, at: Column, mask: str) -> Column:
    """Hash of the words that ``mask`` selects from position ``at`` (from 0); null where the window does not fit."""
    picks = [F.get(words, at + k) for k, bit in enumerate(mask) if bit == "1"]
    return F.when(at + len(mask) <= F.size(words), F.xxhash64(F.lit(mask), *picks))


def _lead(words: Column, at: Column, both: bool) -> Column:
    """Hash of the word at ``at`` and, if ``both``, of the next one: what every seed there begins with."""
    return F.xxhash64(F.get(words, at), F.get(words, at + 1)) if both else F.get(words, at)


def benchmark_seeds(items: DataFrame, both: bool) -> DataFrame:
    """``(mask, hash, pair, item_no, at)`` of ``items(item_no, words)``; each item has the masks of its length."""
    at = items.select("item_no", "words", F.explode(F.sequence(F.lit(0), F.size("words") - 1)).alias("at"))
    served = [(F.size("words") >= low) & (F.size("words") <= (high or 1 << 30)) for _, low, high in MASKS]
    seeds = [F.struct(F.lit(k).alias("mask"), F.when(ok, seed(F.col("words"), F.col("at"), m)).alias("hash")) for k, ((m, *_), ok) in enumerate(zip(MASKS, served, strict=True))]
    pair = _lead(F.col("words"), F.col("at"), both)
    return at.select("item_no", "at", pair.alias("pair"), F.explode(F.array(*seeds)).alias("s")).select("s.mask", "s.hash", "pair", "item_no", "at").where("hash is not null")


def _best_stretch(ours: Column, theirs: Column) -> Column:
    """``(score, equal)`` of the best stretch of two arrays laid on each other; null words never match."""
    same = F.zip_with(ours, theirs, lambda a, b: F.coalesce(a == b, F.lit(False)))
    zero = F.struct(*[F.lit(0).alias(x) for x in ("run", "hits", "score", "equal")])

    def step(acc: Column, hit: Column) -> Column:
        run = acc["run"] + F.when(hit, 1).otherwise(-MISMATCH)
        hits = acc["hits"] + F.when(hit, 1).otherwise(0)
        better = run > acc["score"]
        return F.struct(
            F.greatest(run, F.lit(0)).alias("run"), F.when(run > 0, hits).otherwise(0).alias("hits"),
            F.when(better, run).otherwise(acc["score"]).alias("score"), F.when(better, hits).otherwise(acc["equal"]).alias("equal"),
        )

    return F.aggregate(same, zero, step)


def benchmark_overlaps(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """``doc_id, item_id, start_word, equal_words, item_words, score``: the best stretch of each pair that leaks.

    A pair leaks if its best stretch scores 13, or 0.7 of the item's words if
    that is less; an item of one or two words leaks wherever it stands. Items
    without words match nothing; null and blank texts have none. Repeated
    documents give one row an id and item; null ids are returned as null.
    Empty tables give no rows. Other columns are not looked at. The benchmark
    is broadcast if it has at most 2,000,000 seeds, and joined by a shuffle
    otherwise, of one window of words a position; the texts of what was hit are
    then joined back.
    """
    bench = (
        items.select(F.col(item_col).alias("item_id"), word_hashes(F.col(item_text_col)).alias("words"))
        .where(F.size("words") > 0).distinct()
        .select("item_id", "words", F.xxhash64("item_id", "words").alias("item_no"))
    )
    shortest = bench.agg(F.min(F.size("words"))).first()[0] or 2
    seeds = benchmark_seeds(bench, shortest > 1)
    facts = seeds.agg(F.count("*"), F.collect_set("mask")).first()
    small, masks = facts[0] <= BROADCAST_SEEDS, [(k, MASKS[k][0]) for k in sorted(facts[1]) or range(len(MASKS))]
    near = F.broadcast if small else lambda x: x
    sized = seeds.join(bench.select("item_no", F.size("words").alias("item_words")), "item_no").select("mask", "hash", "item_no", F.col("at").alias("item_at"), "item_words")

    hashed = docs.select(F.col(id_col).alias("doc_id"), word_hashes(F.col(text_col)).alias("words")).where(F.size("words") >= shortest)
    leads = near(seeds.select("pair").distinct())
    if small:
        spots = hashed.select("doc_id", "words", F.posexplode("words").alias("at", "word"))
        paired = spots.withColumn("pair", _lead(F.col("words"), F.col("at"), shortest > 1)).join(leads, "pair", "left_semi")
        keys = [F.struct(F.lit(k).alias("mask"), seed(F.col("words"), F.col("at"), m).alias("hash")) for k, m in masks]
        seeded = paired.select("doc_id", "words", "at", F.explode(F.array(*keys)).alias("s"))
        hits = seeded.select("doc_id", "words", "at", "s.mask", "s.hash").where("hash is not null").join(near(sized), ["mask", "hash"])
    else:
        hashed = hashed.withColumn("text_no", F.xxhash64("words"))
        spots = hashed.select("doc_id", "text_no", "words", F.explode(F.sequence(F.lit(0), F.size("words") - 1)).alias("at"))
        windows = spots.select("doc_id", "text_no", "at", F.slice("words", F.col("at") + 1, SPAN).alias("window"))
        paired = windows.withColumn("pair", _lead(F.col("window"), F.lit(0), shortest > 1)).join(leads, "pair", "left_semi")
        keys = [F.struct(F.lit(k).alias("mask"), seed(F.col("window"), F.lit(0), m).alias("hash")) for k, m in masks]
        seeded = paired.select("doc_id", "text_no", "at", F.explode(F.array(*keys)).alias("s")).select("doc_id", "text_no", "at", "s.mask", "s.hash").where("hash is not null")
        met = seeded.join(sized, ["mask", "hash"]).select("doc_id", "text_no", "item_no", "item_words", (F.col("at") - F.col("item_at")).alias("shift")).distinct()
        texts = hashed.select(F.col("doc_id").alias("i"), F.col("text_no").alias("t"), "words").dropDuplicates(["i", "t"])
        hits = met.join(texts, (F.col("text_no") == F.col("t")) & F.col("doc_id").eqNullSafe(F.col("i"))).select("doc_id", "words", "item_no", "item_words", F.col("shift").alias("at"), F.lit(0).alias("item_at"))
    start = F.col("at") - F.col("item_at")
    inside = F.slice("words", F.greatest(start, F.lit(0)) + 1, F.col("item_words") + F.least(start, F.lit(0)))
    laid = hits.select("doc_id", "item_no", "item_words", start.alias("start_word"), inside.alias("inside"))
    once = laid.groupBy("doc_id", "item_no", "item_words", "start_word", F.xxhash64("inside").alias("as_read")).agg(F.first("inside").alias("inside"))
    near_items = F.broadcast(bench) if small else bench
    both = once.join(near_items, "item_no")
    theirs = F.slice("words", F.greatest(-F.col("start_word"), F.lit(0)) + 1, F.size("inside"))
    scored = both.withColumn("best", _best_stretch(F.col("inside"), theirs))
    enough = F.least(F.lit(FULL_SCORE), F.ceil(F.col("item_words") * SHARE).cast("int"))
    leaks = scored.where(F.col("best.score") >= enough)
    top = F.max(F.struct(F.col("best.score").alias("score"), F.col("best.equal").alias("equal_words"), (-F.col("start_word")).alias("back"), "item_words")).alias("t")
    return leaks.groupBy("doc_id", "item_id").agg(top).select(
        "doc_id", "item_id", (-F.col("t.back")).alias("start_word"), F.col("t.equal_words").alias("equal_words"), F.col("t.item_words").alias("item_words"), F.col("t.score").alias("score")
    )


def drop_contaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents without a leak, with all their columns; a null id falls with any leaking row of a null id."""
    bad = benchmark_overlaps(docs, items, id_col, text_col).select(F.col("doc_id").alias("leaking_id")).distinct()
    return docs.join(bad, docs[id_col].eqNullSafe(bad["leaking_id"]), "left_anti")


def op1_decontamination(spark, sf_dir: str) -> DataFrame:
    """Every pair of a document and a benchmark item that it leaks."""
    return benchmark_overlaps(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
