"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line.

The paper's runs re-expressed on the given tables: motifs, cliques and frequent
subgraphs, the ablations (one-level aggregation, path store and lists), the other
paradigms, shares of a run's phases, peak memory, and the same work on 1, 2, 4
and all cores. Derived graphs are built before the clock starts, as the
reference excludes loading and start-up.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def session(cpus: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def total(df, column="n"):
    return sum(r[column] for r in df.select(column).collect())


def at_scale(cpus: str) -> dict[str, float]:
    """Seconds of the single-thread and speed-up workloads on ``cpus`` cores, after one small run."""
    from embedmine.apps import cliques, fsm, motifs
    from embedmine.sources import derived

    spark = session(cpus)
    dense, custsupp = derived.similar(spark, SF_DIR, 0.26), derived.custsupp(spark, SF_DIR, 45)
    for g in (dense, custsupp):
        g.adjacency.count()
    total(motifs.count_motifs(custsupp, 3))
    runs = {
        "motifs4_dense": lambda: total(motifs.count_motifs(dense, 4)),
        "cliques4_dense": lambda: total(cliques.clique_counts(dense, 4)),
        "fsm_custsupp_theta20": lambda: fsm.frequent_subgraphs(custsupp, 20, 2).patterns.count(),
    }
    out = {}
    for name, run in runs.items():
        began = time.time()
        run()
        out[name] = round(time.time() - began, 3)
    spark.stop()
    return out


def main() -> None:
    spark = session(CPUS)
    from embedmine import metrics
    from embedmine.apps import cliques, fsm, motifs
    from embedmine.baselines import centralized, pattern_centric, vertex_centric
    from embedmine.functions.canonical import words
    from embedmine.operators import layered
    from embedmine.plans.engine import explore
    from embedmine.plans.scratch import written
    from embedmine.sources import derived

    similar = derived.similar(spark, SF_DIR, 0.3)
    dense = derived.similar(spark, SF_DIR, 0.25)
    custsupp = derived.custsupp(spark, SF_DIR, 45)
    docs = derived.shared_line(spark, SF_DIR, 2, 12)
    copart = derived.copart(spark, SF_DIR, 2)
    for g in (similar, dense, custsupp, docs, copart):
        g.adjacency.count()
    counts: dict[str, int] = {}

    level3 = written(motifs.embeddings(dense, 3), "bench")
    shares: dict[str, dict] = {}

    def engine(name, result):
        shares[name] = metrics.phase_shares(result)
        return sum(r["processed"] for r in result.funnel)

    runs = {
        "warm_up": lambda: total(motifs.count_motifs(similar, 3)),
        "motifs3_similar_dense": lambda: total(motifs.count_motifs(dense, 3)),
        "motifs4_similar": lambda: total(motifs.count_motifs(similar, 4)),
        "motifs4_custsupp": lambda: total(motifs.count_motifs(custsupp, 4)),
        "cliques4_similar": lambda: total(cliques.clique_counts(similar, 4)),
        "cliques5_docs": lambda: total(cliques.clique_counts(docs, 5)),
        "fsm_copart_theta10_3_edges": lambda: sum(f.count() for f in fsm.frequent_subgraphs(copart, 10, 3).embeddings.values()),
        "fsm_custsupp_theta20": lambda: sum(f.count() for f in fsm.frequent_subgraphs(custsupp, 20, 2).embeddings.values()),
        "motifs3_two_level": lambda: total(motifs.count_motifs(dense, 3)),
        "motifs3_one_level": lambda: total(motifs.count_motifs(dense, 3, two_level=False)),
        "motifs3_engine_lists": lambda: engine("motifs", explore(similar, motifs.app(3), max_size=3, keep_levels=False)),
        "motifs3_engine_paths": lambda: engine("motifs_paths", explore(similar, motifs.app(3), store="paths", max_size=3, keep_levels=False)),
        "cliques4_engine": lambda: engine("cliques", explore(similar, cliques.app(4))),
        "fsm_copart_engine": lambda: engine("fsm", explore(copart, fsm.app(30, 2))),
        "path_store_build": lambda: layered.build(level3, 3).count(),
        "embedding_lists": lambda: level3.select(*words(3)).count(),
        "vertex_centric_motifs3": lambda: vertex_centric.explore(similar, 3)[0].count(),
        "pattern_centric_copart": lambda: len(pattern_centric.frequent_patterns(copart, 10, 2)),
        "census4_similar": lambda: total(centralized.motif_census(similar, 4)),
    }
    seconds = {}
    for name, run in runs.items():
        began = time.time()
        counts[name] = run()
        seconds[name] = round(time.time() - began, 3)
    seconds.pop("warm_up")
    main_runs = [k for k in seconds if k.startswith(("motifs3_similar", "motifs4", "cliques4_similar", "cliques5", "fsm_copart_theta10", "fsm_cust"))]
    memory = metrics.peak_memory_mb(spark)
    code = {"motifs": metrics.lines_of_code(motifs.app), "cliques": metrics.lines_of_code(cliques.app), "fsm": metrics.lines_of_code(fsm.app)}
    spark.stop()
    scaling = {c: at_scale(c) for c in dict.fromkeys(("1", "2", "4", CPUS)) if int(c) <= int(CPUS)}
    print(
        json.dumps(
            {
                "metric": "seconds of the motif, clique and frequent-subgraph runs",
                "value": round(sum(seconds[k] for k in main_runs), 3),
                "unit": "sec",
                "queries": seconds,
                "sf": SF_DIR.rstrip("/").rsplit("sf", 1)[-1],
                "embeddings": counts,
                "embeddings_per_sec": {k: round(counts[k] / seconds[k]) for k in main_runs},
                "ratios": {"one_level_slowdown": round(seconds["motifs3_one_level"] / seconds["motifs3_two_level"], 2), "list_words_per_store_edge": round(3 * counts["embedding_lists"] / max(1, counts["path_store_build"]), 2), "paths_against_lists": round(seconds["motifs3_engine_paths"] / seconds["motifs3_engine_lists"], 2)},
                "phase_shares": shares,
                "peak_heap_mb": memory,
                "lines_of_code": code,
                "seconds_by_cores": scaling,
                "speedup": {c: {k: round(scaling["1"][k] / x, 2) for k, x in v.items()} for c, v in scaling.items()},
            }
        )
    )


if __name__ == "__main__":
    main()
