"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Times are of a warm session with graphs prepared and cached, as the published
ones leave out start-up, first load and final writing. ``python bench.py
--workload`` runs all hundred queries instead of four of two and three keywords, and the grid of K
of 1, 2, 5 and 10 on the contact graph, and prints its measures to stderr; ``--scaling`` runs two searches on
1, 2, 4 and 8 cores.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from relq.baselines import waves
from relq.graph import builders
from relq.measures import report
from relq.schema import RelGraph
from relq.search.batch import batch_search
from relq.search.driver import relationship_search
from relq.text.index import build_index
from relq.text.lookup import find_seeds
from relq.workload import queries as w

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
PLAIN = ("graph_fk_edges", "edge_length_tau", "mirror_edges", "index_postings_df", "seed_lookup_token", "op_join_sortmerge", "op_self_cooccur", "op_join_asof_event", "op_win_row_number", "op_agg_cube", "st_tumbling")


def session() -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def cached(g: RelGraph) -> RelGraph:
    g = RelGraph(g.vertices.persist(), g.edges.persist(), g.tau, g.scheme)
    g.edges.count(), g.vertices.count()
    return g


def one_search(m: int) -> None:
    """One search of m keywords on the contact graph in this process; prints its seconds."""
    spark = session()
    contact = cached(builders.contact_graph(spark, SF_DIR))
    s = find_seeds(build_index(contact.vertices), contact.vertices, w.TERMS[:m]).persist()
    s.count()
    relationship_search(contact, s, m, 1, max_supersteps=1)
    print(report.timed(lambda: relationship_search(contact, s, m, 1))[1])


def scaling() -> None:
    """Seconds and efficiency of two searches by number of cores, each in a process of its own."""
    for m in (2, 3):
        took = {}
        for cores in (1, 2, 4, 8):
            done = subprocess.run([sys.executable, __file__, f"--one={m}"], env=os.environ | {"BENCH_CPUS": str(cores)}, capture_output=True, text=True, check=True)
            took[cores] = round(float(done.stdout.split()[-1]), 2)
        print(json.dumps({"m": m, "seconds": took, "efficiency": {p: round(x, 2) for p, x in report.parallel_efficiency(took).items()}}))


def main() -> None:
    spark, took = session(), {}
    from relq.plans import registry

    def clock(name: str, f) -> object:
        t = time.time()
        out = f()
        took[name] = round(time.time() - t, 3)
        print(name, took[name], file=sys.stderr, flush=True)
        return out

    spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count().collect()
    for name in PLAIN:
        clock(name, lambda n=name: registry.QUERIES[n](spark, SF_DIR).write.format("noop").mode("overwrite").save())

    fk = cached(builders.fk_graph(spark, SF_DIR))
    index = build_index(fk.vertices).persist()
    seeds = find_seeds(index, fk.vertices, ["anvil", "asia"]).persist()
    clock("bfs_fk", lambda: waves.parallel_bfs(fk, seeds.where("mask = 2"))[0].count())
    pair = find_seeds(index, fk.vertices, ["asia", "anvil"]).withColumn("query_id", F.lit(0)).select("query_id", "node_id", "mask")
    clock("fk_k1", lambda: batch_search(fk, pair, {0: 2})[0].collect())
    fk.edges.unpersist()

    ids = list(range(100)) if "--workload" in sys.argv else [9, 19, 29, 39]
    content, seeds, queries = w.content_batch(spark, SF_DIR, ids)
    seeds = seeds.persist()
    content.edges.count(), seeds.count()
    clock("workload_k1", lambda: batch_search(content, seeds, queries)[0].collect())  # to their own end
    took["workload_mean_k1"] = round(took["workload_k1"] / len(queries), 3)
    content.edges.unpersist()

    contact = cached(builders.contact_graph(spark, SF_DIR))
    rows = []
    for k in (1, 2, 5, 10) if "--workload" in sys.argv else (1,):
        for m in (2, 3) if "--workload" in sys.argv else (2,):
            s = find_seeds(build_index(contact.vertices), contact.vertices, w.TERMS[:m]).persist()
            found, seconds = report.timed(lambda s=s, m=m, k=k: relationship_search(contact, s, m, k, measures=True))
            took[f"contact_m{m}_k{k}"] = round(seconds, 3)
            rows.append(report.report_row(len(rows), m, k, found, seconds, s.count()))
    if "--workload" in sys.argv:
        print(report.report(spark, rows).toPandas().to_string(), file=sys.stderr)
    print(json.dumps({"metric": "total seconds of the headline queries", "value": round(sum(took.values()) - took["workload_mean_k1"], 3), "unit": "sec", "queries": took, "sf": SF_DIR.rsplit("/", 1)[-1]}))


if __name__ == "__main__":
    one = [a for a in sys.argv if a.startswith("--one=")]
    if one:
        one_search(int(one[0][6:]))
    elif "--scaling" in sys.argv:
        scaling()
    else:
        main()
