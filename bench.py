"""Headline queries and the rates of all techniques; prints one JSON line.

``BENCH_SF_DIR`` names the tables (default sf0.1), ``BENCH_CPUS`` the threads.
``techniques`` holds updates, scans and reads a second of every technique over a
dense workload and two of texts, each the mean of RUNS runs beside its relative
deviation.  ``python bench.py scale`` prints how rounds and clustering move with
the size of the tables and the threads instead.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

from driftview import queries as core
from driftview.operators.baselines import NaiveView
from driftview.operators.driver_view import DriverView
from driftview.operators.measures import rel_std, speedups
from driftview.operators.view import ClassificationView, Options
from driftview.plans import workloads
from driftview.session import build_session, materialize

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
#: As many warm examples as in the published runs, then rounds of EACH examples, and runs of every measure.
WARM, EACH, RUNS = 12_000, 20, 7
HEADLINE = ("round_ledger", "lazy_ledger", "eager_view_final", "eager_view_memory", "lazy_count", "hybrid_sources", "naive_eager_view", "cost_family", "ovr_multiclass", "tf_bag_of_terms", "view_cube", "quality_title7")


def timed(f) -> float:  # noqa: ANN001
    began = time.perf_counter()
    f()
    return round(time.perf_counter() - began, 3)


def per_second(f, times: int, runs: int = RUNS) -> tuple[float, float]:  # noqa: ANN001
    """``times`` over the mean seconds of ``runs`` calls, and their relative deviation."""
    seconds = []
    for _ in range(runs):
        began = time.perf_counter()
        f()
        seconds.append(time.perf_counter() - began)
    return round(times * runs / sum(seconds), 2), round(rel_std(seconds), 3)


def datasets(spark) -> list[workloads.Workload]:  # noqa: ANN001
    """Dense rows, first words, and whole texts, with as many warm examples as there are up to WARM."""
    found = [workloads.planted_lineitem(spark, SF_DIR), workloads.text_language(spark, SF_DIR, 7), workloads.text_language(spark, SF_DIR)]
    for w, name in zip(found, ("dense", "title7", "full_text"), strict=True):
        w.name = name
        n = w.source.count()
        w.measured = 2 * RUNS * EACH
        w.warm = min(WARM, n - w.measured)
    return found


def rates(spark, chosen: tuple[str, ...] = ("dense", "title7", "full_text")) -> dict[str, dict]:  # noqa: ANN001
    """Per workload and technique: eager updates, lazy updates, lazy scans and single reads a second, and rows scored for each round.

    Updates come in batches of EACH, as a micro-batch brings them.  Reads come in
    one batch of 15,000 ids, and as single look-ups.
    """
    out = {}
    for w in datasets(spark):
        if w.name not in chosen:
            continue
        entities = materialize(w.entities, "bench")
        n = entities.count()
        batch = w.batch()
        warm, rest = w.trainer.fit([(f, y) for _, f, y in batch[: w.warm]], w.dim), batch[w.warm :]
        ids = materialize(workloads.random_ids(entities, 15_000), "ids")
        some = [r["id"] for r in ids.limit(RUNS).collect()]
        out[w.name] = {}
        for name in (*core.TECHNIQUES, *(["incremental_driver"] if w.name == "dense" else [])):
            kind, _, arch = name.partition("_")

            def make(policy: str):  # noqa: ANN202
                if kind == "naive":  # noqa: B023
                    return NaiveView(entities, w.trainer, warm, policy, arch)  # noqa: B023
                if arch == "driver":  # noqa: B023
                    return DriverView(entities, w.trainer, w.dim, Options(policy=policy), warm)  # noqa: B023
                return ClassificationView(entities, w.trainer, w.dim, Options(policy=policy, arch=arch or "hybrid"), warm)  # noqa: B023

            def rounds(view) -> tuple[float, float]:  # noqa: ANN001
                parts = iter([rest[k : k + EACH] for k in range(0, len(rest), EACH)])  # noqa: B023
                view.update(next(parts))  # the first round warms up
                return per_second(lambda: view.update(next(parts)), EACH)

            row, before, began = {}, cached_mb(spark), time.perf_counter()
            eager = make("eager")
            row["load_s"], row["cached_mb"] = round(time.perf_counter() - began, 2), round(cached_mb(spark) - before, 1)
            lazy = make("lazy")
            row["eager_updates_s"], row["eager_deviation"] = rounds(eager)
            row["rows_per_round"] = n if kind == "naive" else round(sum(s.n_band for s in eager.history) / max(1, len(eager.history)))
            row["lazy_updates_s"], row["lazy_deviation"] = rounds(lazy)
            lazy.count_members(1)
            row["lazy_scans_s"], row["scan_deviation"] = per_second(lambda: lazy.count_members(1), 1)  # noqa: B023
            for policy, view in (("eager", eager), ("lazy", lazy)):
                view.label_of_many(ids).count()
                row[f"{policy}_reads_s"], _ = per_second(lambda v=view: v.label_of_many(ids).agg({"class": "sum"}).collect(), ids.count(), 3)  # noqa: B023
            one = iter(some * 2)
            row["single_reads_s"], _ = per_second(lambda: eager.label_of(next(one)), 1)  # noqa: B023
            for view in (eager, lazy):
                view.close()
            out[w.name][name] = row
        for measure in ("eager_updates_s", "lazy_scans_s"):
            out[w.name][f"gain_{measure}"] = {k: round(v, 2) for k, v in speedups({k: r[measure] for k, r in out[w.name].items() if k in core.TECHNIQUES or k == "incremental_driver"}, "naive_disk").items()}
    return out


def cached_mb(spark) -> float:  # noqa: ANN001
    """Megabytes that cached tables take in memory now."""
    return sum(x.memSize() for x in spark.sparkContext._jsc.sc().getRDDStorageInfo()) / 1e6


def buffer_reads(spark) -> list[dict]:  # noqa: ANN001
    """Reads a second of a hybrid view, by the share of entities in the band and in the buffer."""
    w = workloads.planted_lineitem(spark, SF_DIR)
    entities = materialize(w.entities, "sweep")
    ids = materialize(workloads.random_ids(entities, 15_000), "ids")
    warm, rows = w.trainer.fit([(f, y) for _, f, y in w.batch()], w.dim), []
    for buffer in (1, 5, 20, 100):
        view = ClassificationView(entities, w.trainer, w.dim, Options(policy="lazy", arch="hybrid", buffer_share=buffer / 100), warm)
        reach = view.store.read().selectExpr("percentile_approx(abs(eps), array(0.01, 0.1, 0.5)) AS q").first()["q"]
        for share, width in zip((1, 10, 50), reach, strict=True):
            view.marks.reset()
            view.marks.push(width / view.largest, 0.0)  # as wide as if the weights had moved so far
            view.label_of_many(ids).count()
            reads, _ = per_second(lambda: view.label_of_many(ids).agg({"class": "sum"}).collect(), ids.count(), 3)  # noqa: B023
            rows.append({"band_percent": share, "buffer_percent": buffer, "reads_s": reads})
        view.close()
    return rows


def scale() -> None:
    """Seconds of a clustering, of an eager round and of a class count, by tables and threads."""
    rows = []
    for size in ("sf0.001", "sf0.01", "sf0.1"):
        for threads in (1, 2, 4, 8):
            spark = build_session("scale", threads, threads)
            spark.sparkContext.setLogLevel("ERROR")
            w = workloads.planted_lineitem(spark, str(Path(SF_DIR).parent / size))
            entities = materialize(w.entities, "scale")
            batch = w.batch()
            warm = w.trainer.fit([(f, y) for _, f, y in batch[: w.warm]], w.dim)
            ClassificationView(entities, w.trainer, w.dim, Options(), warm)  # warms up
            began = time.perf_counter()
            view = ClassificationView(entities, w.trainer, w.dim, Options(), warm)
            cluster = time.perf_counter() - began
            view.update(batch[w.warm : w.warm + 4])
            parts = iter([batch[k : k + 4] for k in range(w.warm + 4, len(batch), 4)])
            rounds, _ = per_second(lambda: view.update(next(parts)), 1)  # noqa: B023
            counts, _ = per_second(lambda: view.count_members(1), 1)  # noqa: B023
            rows.append({"tables": size, "threads": threads, "entities": entities.count(), "cluster_s": round(cluster, 2), "round_s": round(1 / rounds, 3), "count_s": round(1 / counts, 3)})
            spark.stop()
    print(json.dumps(rows))


def main() -> None:
    spark = build_session("bench", os.environ.get("BENCH_CPUS", "8"), 8)
    spark.sparkContext.setLogLevel("ERROR")
    spark.range(1000).count()
    all_ = core.queries()
    per = {name: timed(lambda q=all_[name]: q(spark, SF_DIR).write.format("noop").mode("overwrite").save()) for name in HEADLINE}
    line = {"metric": "headline_queries_total", "value": round(sum(per.values()), 3), "unit": "sec", "queries": per, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf")}
    line["techniques"] = rates(spark)
    line["buffer_reads"] = buffer_reads(spark)
    print(json.dumps(line))


if __name__ == "__main__":
    sys.exit(scale() if sys.argv[1:] == ["scale"] else main())
