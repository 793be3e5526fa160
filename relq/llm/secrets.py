"""Secrets in whole texts: three fixed patterns, and runs that a Markov model takes for random.

Two first-order models over characters, of random strings and of ordinary
identifiers, are counted from labelled samples. A run of identifier characters
is a secret if its log-likelihood ratio is high enough. Everything is built
from DataFrame functions; the models are one constant array of 128 x 128
ratios.
"""

from __future__ import annotations

import math
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed patterns, in the order in which spans with equal starts are listed.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}"
HEX = r"[0-9a-f]{32,}"
ASSIGN_LENGTH = 8
KINDS = ("assign", "access", "hex", "markov")
#: Runs the models judge, and the ratio (natural logarithm) above which they are secrets.
RUN = r"[A-Za-z0-9+/_=-]{20,}"
LEAST_RATIO, ALPHABET = 18.0, 128
SAMPLE_DOCS, SAMPLE_STRINGS = 2_000, 6_000
#: Fixed words from which ordinary identifiers are composed.
WORDS = (
    "user name file path index value count total list map table column row key id type class method function object string number "
    "array config option default parent child node edge graph page link image button view model controller service client server "
    "request response error message event handler listener manager factory builder parser writer reader stream buffer cache session "
    "account customer order product price date time start end first last next previous current width height color size label title "
    "text content header footer body left right top bottom update create delete insert select search filter sort group join"
).split()


def labelled_samples(spark: SparkSession, docs: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(run, random)``: digests in hex and base64, composed identifiers, and words of a bounded sample of documents.

    The sample is the 2,000 documents whose ids hash lowest; of their runs of
    eight characters or more only those of letters alone are ordinary.
    """
    n = spark.range(SAMPLE_STRINGS)
    digest = F.sha2(F.concat(F.lit("sample"), F.col("id").cast("string")), 256)
    b64 = F.substring(F.base64(F.unhex(digest)), 1, 40)
    random = n.select(F.explode(F.array(F.substring(digest, 1, 40), b64, F.translate(b64, "+/", "-_"), F.upper(F.translate(b64, "+/", "Q7")))).alias("run"), F.lit(True).alias("random"))
    words = F.array(*[F.lit(w) for w in WORDS])
    pick = lambda k: F.get(words, F.pmod(F.xxhash64(F.col("id"), F.lit(k)), F.lit(len(WORDS))).cast("int"))
    three = [pick(k) for k in range(3)]
    forms = [F.concat_ws("_", *three), F.concat_ws("-", *three), F.concat_ws("/", *three), F.concat(three[0], F.initcap(three[1]), F.initcap(three[2])), F.upper(F.concat_ws("_", *three)), F.concat(three[0], F.initcap(three[1]), (F.col("id") % 10).cast("string"))]
    ordinary = n.select(F.explode(F.array(*forms)).alias("run"), F.lit(False).alias("random"))
    samples = random.unionByName(ordinary)
    if docs is not None:
        ids = docs.select(F.col(id_col).alias("i")).where("i is not null").orderBy(F.xxhash64("i"), "i").limit(SAMPLE_DOCS).distinct()
        some = docs.select(F.col(id_col).alias("i"), F.col(text_col).cast("string").alias("t")).join(F.broadcast(ids), "i").where("t is not null")
        runs = some.select(F.explode(F.regexp_extract_all("t", F.lit("[A-Za-z]{8,}"), F.lit(0))).alias("run"), F.lit(False).alias("random"))
        samples = samples.unionByName(runs)
    return samples


def _codes(run: Column) -> Column:
    return F.transform(F.split(run, ""), lambda c: F.least(F.ascii(c), F.lit(ALPHABET - 1)))


def transition_ratios(samples: DataFrame, smoothing: float = 0.5) -> list[float]:
    """Natural log of P(random) / P(ordinary) for each pair of character codes, from ``(run, random)``.

    Null runs and labels and runs of one character are ignored; without samples every ratio is 0.
    """
    codes = samples.where("run is not null and random is not null and length(run) > 1").select("random", _codes(F.col("run")).alias("c"))
    pairs = codes.select("random", F.explode(F.transform(F.sequence(F.lit(0), F.size("c") - 2), lambda k: F.get("c", k) * ALPHABET + F.get("c", k + 1))).alias("pair"))
    counts: dict[bool, dict[int, int]] = {True: {}, False: {}}
    for row in pairs.groupBy("random", "pair").count().collect():  # 2 x 128 x 128 rows at most
        counts[row["random"]][row["pair"]] = row["count"]
    seen = sorted({p % ALPHABET for c in counts.values() for p in c} | {p // ALPHABET for c in counts.values() for p in c})
    if not counts[True] or not counts[False]:
        return [0.0] * (ALPHABET * ALPHABET)

    def log_p(count: dict[int, int]) -> dict[int, float]:
        out = {}
        for a in seen:
            total = sum(count.get(a * ALPHABET + b, 0) for b in seen) + smoothing * len(seen)
            out |= {a * ALPHABET + b: math.log((count.get(a * ALPHABET + b, 0) + smoothing) / total) for b in seen}
        return out

    one, other = log_p(counts[True]), log_p(counts[False])
    return [round(one[p] - other[p], 6) if p in one else 0.0 for p in range(ALPHABET * ALPHABET)]


def log_ratio(run: Column, ratios: list[float]) -> Column:
    """Sum of the transition ratios along ``run``."""
    table = F.lit(ratios)
    start = F.struct(F.lit(-1).alias("last"), F.lit(0.0).alias("sum"))
    return F.aggregate(
        _codes(run), start,
        lambda acc, c: F.struct(c.alias("last"), (acc["sum"] + F.when(acc["last"] < 0, F.lit(0.0)).otherwise(F.get(table, acc["last"] * ALPHABET + c))).alias("sum")),
        lambda acc: acc["sum"],
    )


def _spans(text: Column, pattern: str, kind: str, may: Column) -> Column:
    """``array<struct<start, order, stop, kind, run, value>>`` of all matches, in code points, stop exclusive."""
    runs = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = F.regexp_extract_all(text, F.lit(pattern), F.lit(2)) if kind == "assign" else runs
    parts = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), runs.alias("run"), values.alias("value"))
    order = KINDS.index(kind)
    empty = F.array().cast("array<struct<start:int,order:int,stop:int,kind:string,run:string,value:string>>")

    def step(acc: Column, part: Column) -> Column:
        begin = acc["at"] + F.length(part["gap"])
        stop = begin + F.length(part["run"])
        span = F.struct(begin.alias("start"), F.lit(order).alias("order"), stop.alias("stop"), F.lit(kind).alias("kind"), part["run"].alias("run"), part["value"].alias("value"))
        return F.struct(stop.alias("at"), F.concat(acc["found"], F.array(span)).alias("found"))

    all_parts = F.slice(parts, 1, F.size(runs))
    found = F.aggregate(all_parts, F.struct(F.lit(0).alias("at"), empty.alias("found")), step, lambda acc: acc["found"])
    return F.when(may, found).otherwise(empty)


def secret_spans(docs: DataFrame, ratios: list[float], id_col: str = "doc_id", text_col: str = "text", least_ratio: float = LEAST_RATIO) -> DataFrame:
    """``doc_id, base, added``, one row per input row: spans of the patterns, and those that the models add.

    A span is ``struct<start, order, stop, kind, run, value>`` in code points,
    stop exclusive; both arrays are sorted by start and kind. Matches of a kind
    are leftmost and do not overlap; assigned values of under eight characters
    are dropped after matching. Runs that overlap a span of the patterns are
    not added. A null text counts as empty; repeated rows are repeated; other
    columns are not looked at.
    """
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("body"))
    return rows.select("doc_id", *span_columns(F.col("body"), ratios, least_ratio)).select("doc_id", "base", added_column())


def span_columns(body: Column, ratios: list[float], least_ratio: float = LEAST_RATIO) -> list[Column]:
    lower = F.lower(body)
    named = F.contains(lower, F.lit("passw")) | F.contains(lower, F.lit("secret")) | F.contains(lower, F.lit("token")) | F.contains(lower, F.lit("api_key")) | F.contains(lower, F.lit("apikey"))
    assign = F.filter(_spans(body, ASSIGN, "assign", named), lambda s: F.length(s["value"]) >= ASSIGN_LENGTH)
    access = _spans(body, ACCESS, "access", F.contains(body, F.lit("AKIA")))
    hexes = _spans(body, HEX, "hex", body.rlike(HEX))
    judged = F.filter(_spans(body, RUN, "markov", body.rlike(RUN)), lambda s: log_ratio(s["run"], ratios) >= least_ratio)
    return [F.array_sort(F.concat(assign, access, hexes)).alias("base"), judged.alias("judged")]


def added_column() -> Column:
    return F.filter("judged", lambda s: ~F.exists("base", lambda b: (b["start"] < s["stop"]) & (s["start"] < b["stop"]))).alias("added")


def _listed(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))))


def redact(docs: DataFrame, ratios: list[float], text_col: str = "text", length_col: str | None = "n_chars", mark: str = "[SECRET]") -> DataFrame:
    """``docs`` with every span replaced by ``mark``; assigned values keep their names. Null texts stay null."""
    names, own = docs.columns, uuid.uuid4().hex  # columns of ours that clash with none
    body, judged, base = F.coalesce(F.col(text_col).cast("string"), F.lit("")), f"judged_{own}", f"base_{own}"
    spans = span_columns(body, ratios)
    marked = docs.withColumns({judged: spans[1], base: spans[0]})
    added = F.filter(judged, lambda s: ~F.exists(base, lambda b: (b["start"] < s["stop"]) & (s["start"] < b["stop"])))
    cut = F.transform(F.array_sort(F.concat(F.col(base), added)), lambda s: F.struct((s["stop"] - F.length(s["value"])).alias("start"), s["stop"].alias("stop")))
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        return F.struct(
            F.greatest(acc["at"], s["stop"]).alias("at"),
            F.when(fresh, F.concat(acc["out"], F.substring(body, acc["at"] + 1, s["start"] - acc["at"]), F.lit(mark))).otherwise(acc["out"]).alias("out"),
        )

    clean = F.aggregate(F.array_sort(cut), start, step, lambda acc: F.concat(acc["out"], F.substring(body, acc["at"] + 1, F.length(body))))
    text = F.when(F.size(cut) > 0, clean).otherwise(F.col(text_col))
    out = marked.withColumn(text_col, text)
    if length_col in names:
        out = out.withColumn(length_col, F.when(F.size(base) + F.size(judged) > 0, F.length(text_col)).otherwise(F.col(length_col)).cast(docs.schema[length_col].dataType))
    return out.select(*[F.col(f"`{n}`") for n in names])


def op4_secrets(spark, sf_dir: str) -> DataFrame:
    """Every document with its spans and the digest of those of the fixed patterns."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = secret_spans(docs, transition_ratios(labelled_samples(spark, docs)))
    n = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select(
        "doc_id", n("assign"), n("access"), n("hex"), F.sha2(_listed(F.col("base")), 256).alias("base_sha256"),
        _listed(F.array_sort(F.concat("base", "added"))).alias("spans"), F.size("added").cast("long").alias("n_markov"),
    )
