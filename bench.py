"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``queries`` has one run of each query of the two mixes by either engine at that scale. ``flat`` is mixTime of either engine
(mean of 3 runs) at this scale and at a hundredth of it; ``deep`` has, for each query, the seconds of the plain engine (t)
and of the provenance engine on one answer (tinst) at a tenth of the scale (mean of 5 runs) and at it (t10, tinst10; mean
of $BENCH_RUNS, 1 by default), and the unions. Answers are picked before any clock runs. A run over 40 minutes is a timeout (null).
"""

from __future__ import annotations

import json
import os
import time
from pathlib import Path


def main() -> None:
    from pyspark.sql import SparkSession

    folder, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from derivatrace.operators import explain
    from derivatrace.operators.measures import mix_time, overhead, run, timed, union_count
    from derivatrace.operators.provenance import certain_answers, compute_provenance
    from derivatrace.plans.cq import instantiate
    from derivatrace.workloads.mixes import DEEP, FLAT
    from derivatrace.workloads.queries import flat, picked, survey

    def plain(where, q):
        return lambda: certain_answers(survey(spark, where), DEEP[q].cq)

    def explained(where, q, row):
        return lambda: explain.why(survey(spark, where), DEEP[q].cq, row)

    def sibling(factor: float) -> str | None:
        scale = float(Path(folder).name.removeprefix("sf")) * factor
        where = Path(folder).parent / f"sf{scale:g}"
        return str(where) if where.is_dir() else None

    answers: dict[tuple[str, str], dict] = {}

    def pick(where: str) -> None:
        for q, d in DEEP.items():
            rows = picked(spark, where, d.cq) if d.cq.head else [{}]
            answers[where, q] = rows[0] if rows else {}

    small, tenth = sibling(0.01), sibling(0.1)
    seconds = lambda x: None if x is None else round(x, 3)
    mixes = {"prov": lambda where, q: lambda: compute_provenance(flat(spark, where), FLAT[q]), "certain": lambda where, q: lambda: certain_answers(flat(spark, where), FLAT[q])}
    run(mixes["prov"](folder, "F1")())  # the first query also starts the session
    out: dict = {"flat": {}, "deep": {}}
    for where in filter(None, (small, folder)):
        times = {kind: mix_time([make(where, q) for q in FLAT], runs=3) for kind, make in mixes.items()}
        out["flat"][Path(where).name] = {"provenance": seconds(times["prov"]), "baseline": seconds(times["certain"]), "overhead": round(overhead(times["prov"], times["certain"]), 3)}
    for where in filter(None, (tenth, folder)):
        pick(where)
    took: dict[str, float | None] = {}
    for q in FLAT:
        for kind, make in mixes.items():
            began = time.perf_counter()
            run(make(folder, q)())
            took[f"{kind}_{q}"] = round(time.perf_counter() - began, 3)
    few = int(os.environ.get("BENCH_RUNS", "1"))
    for q in DEEP:
        row = {"unf_base": union_count(survey(spark, folder), DEEP[q].cq, certain=True), "unf": union_count(survey(spark, folder), DEEP[q].cq), "uinst": union_count(survey(spark, folder), instantiate(DEEP[q].cq, answers[folder, q]))}
        for where, suffix, runs in ((tenth, "", 5), (folder, "10", few)):
            if where is not None:
                row["t" + suffix] = seconds(timed(plain(where, q), runs))
                row["tinst" + suffix] = seconds(timed(explained(where, q, answers[where, q]), runs))
                row["prov" + suffix] = explained(where, q, answers[where, q])().count()
        took[f"certain_{q}"], took[f"inst_{q}"] = row["t10"], row["tinst10"]
        out["deep"][q] = row
    here = out["flat"][Path(folder).name]
    print(json.dumps({"metric": "total seconds of the flat and the deep mix", "value": round(sum(filter(None, took.values())), 3), "unit": "sec", "queries": took, "sf": Path(folder).name, "mix_time": here, **out}))
    spark.stop()


if __name__ == "__main__":
    main()
