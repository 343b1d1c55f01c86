"""One JSON line: seconds of the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]. --experiment [--labels] [--edges] runs the
published experiment instead: rebuilding (FULL) against maintaining (INCR), means, gains and claims."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def session() -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "16g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(f) -> float:
    t = time.time()
    f().write.format("noop").mode("overwrite").save()
    return round(time.time() - t, 3)


def experiment(spark: SparkSession, views: dict[str, tuple[str, ...]], fractions: tuple[float, ...], samples: tuple[str, ...], reps: int = 2, sf: str = SF) -> list[tuple]:
    """(sample, workload, fraction, view, regime, rep, ms, rho): rebuilding a view of the updated graph against maintaining
    it from the base graph's, whose first build is not counted. sample: "labels" (whole labels come, whether the view
    reads them or not) or "edges" (a share of each label's edges). rho: inserted edges in % of the base graph's, over all
    labels. The first repetition of each pair warms up and is left out of the result."""
    from pathloom.functions import measures
    from pathloom.operators.engine import LabeledGraph, maintain, materialize, staged_update
    from pathloom.plans.rules import slice_labels
    from pathloom.queries import SOURCES, materialized
    from pathloom.sources.graphs import relations
    from pathloom.sources.staging import KEPT_ROWS, Stage
    from pathloom.views import VIEWS

    out = []
    for workload, names in views.items():
        family = VIEWS[names[0]][0]
        stage = Stage(spark, "bench")
        every = relations(spark, sf, SOURCES[family]())
        whole = {k: stage.put(d) for k, d in every.items()}
        total = sum(n for _, n in whole.values())
        for name in names:
            _, p, label = VIEWS[name]
            own = sorted(slice_labels(p, label) & set(whole))
            graph = LabeledGraph.from_relations(spark, {k: whole[k][0] for k in own})
            for sample in samples:
                for f in fractions:
                    work = Stage(spark, "bench-view")
                    if sample == "labels":
                        chosen = measures.sample_labels(whole, f)
                        base, u = measures.split_by_labels(graph, chosen)
                        new = sum(whole[k][1] for k in chosen)
                    else:
                        base, u = measures.split_by_edges(graph, round(100 * f))
                        new = f * total
                    program, full = materialized(p, base, label, work)
                    u = staged_update(u, work)
                    for rep in range(reps + 1):
                        t = time.time()
                        again = LabeledGraph.from_relations(spark, {k: whole[k][0] for k in own})
                        again.sizes = {(k, False): whole[k][1] for k in own}
                        work.keep(materialize(program, again, [label], stage=work).rel(label), max(again.sizes.values()) <= KEPT_ROWS)
                        ms = {"FULL": 1000 * (time.time() - t)}
                        t = time.time()
                        maintain(program, full, u, stage=work)
                        ms["INCR"] = 1000 * (time.time() - t)
                        out += [(sample, workload, f, name, regime, rep, x, 100.0 * new / (total - new)) for regime, x in ms.items() if rep]
                    work.clear()
        stage.clear()
    return out


def report(spark: SparkSession, rows: list[tuple]) -> dict:
    """The means, gains and claims of an experiment, by sample."""
    from pyspark.sql import functions as F

    from pathloom.functions import measures

    t = spark.createDataFrame(rows, "sample string, workload string, fraction double, view string, regime string, rep int, ms double, rho double")
    out = {}
    for sample in sorted({r[0] for r in rows}):
        own = t.where(F.col("sample") == sample)
        means = measures.mean_ms(own)
        rho = own.groupBy("workload", "fraction").agg(F.first("rho").alias("rho"))
        table = measures.gains(means).join(rho, ["workload", "fraction"]).orderBy("workload", "fraction")
        claims = measures.claim_sparser_better(means).collect()
        out[sample] = {
            "table": [{k: round(v, 2) if isinstance(v, float) else v for k, v in r.asDict().items()} for r in table.collect()],
            "always_positive": measures.claim_positive(means).first()[0], "sparser_better": {r["fraction"]: r["sparser_better"] for r in claims},
            "views": {f"{r['view']}": [round(r["FULL"]), round(r["INCR"])] for r in own.groupBy("view").pivot("regime", ["FULL", "INCR"]).avg("ms").orderBy("view").collect()},
        }
    return out


def main() -> None:
    from pathloom.queries import QUERIES

    spark = session()
    if "--experiment" in sys.argv:
        from pathloom.functions import measures
        from pathloom.views import DENSE, SPARSE

        samples = tuple(x for x in ("labels", "edges") if f"--{x}" in sys.argv) or ("labels", "edges")
        print(json.dumps(report(spark, experiment(spark, {"dense": DENSE, "sparse": SPARSE}, measures.FRACTIONS, samples))))
        return
    names = [*(f"view_d{k}" for k in range(1, 11)), *(f"view_s{k}" for k in range(1, 11)), "incr_d5", "incr_d8", "incr_s3"]
    QUERIES["view_d2"](spark, SF).count()  # starts the session
    times = {n: timed(lambda n=n: QUERIES[n](spark, SF)) for n in names}
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": float(SF.rstrip("/").rpartition("sf")[2] or 0)}))


if __name__ == "__main__":
    main()
