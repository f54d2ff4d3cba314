"""Times the headline queries and prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from webtext.plans import CATALOGUE  # noqa: E402
from webtext.session import local  # noqa: E402

HEADLINE = [
    "extract_core", "template_lsh", "propagated_main", "inference_share", "content_list", "markdown", "rouge5_pages", "rulebook_main", "strip_all_text", "density_text",
    "exact_dedup", "lang_vote", "q_reasons", "q_gram_repetition", "fuzzy_dedup", "attrition", "benchmark_overlap", "ratio_histogram", "weighted_win_rate", "lm_cross_entropy",
]


def cost_after(spark, stage: int) -> tuple[int, float, float]:
    """(last stage, MB shuffled, MB spilled to disk) of the stages after the given one, from Spark's own status store."""
    sc = spark.sparkContext
    none = sc._jvm.java.util.ArrayList()
    stages = sc._jsc.sc().statusStore().stageList(none, False, False, sc._gateway.new_array(sc._jvm.double, 0), none)
    new = [s for s in (stages.apply(i) for i in range(stages.size())) if s.stageId() > stage]
    mb = lambda values: round(sum(values) / 2**20, 1)
    return max([stage, *(s.stageId() for s in new)]), mb(s.shuffleWriteBytes() for s in new), mb(s.diskBytesSpilled() for s in new)


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local(os.environ.get("BENCH_CPUS", "8"), 16)
    spark.sparkContext.setLogLevel("ERROR")
    CATALOGUE["scan_pages"].run(spark, sf_dir).write.format("noop").mode("overwrite").save()
    took, shuffled, spilled = {}, {}, {}
    stage = cost_after(spark, -1)[0]
    for name in HEADLINE:
        start = time.perf_counter()
        CATALOGUE[name].run(spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - start, 3)
        stage, shuffled[name], spilled[name] = cost_after(spark, stage)
    share = CATALOGUE["inference_share"].run(spark, sf_dir).first()
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").count()
    print(json.dumps({
        "metric": "headline queries, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": Path(sf_dir).name.removeprefix("sf"),
        "pages_per_second": round(pages / took["extract_core"], 1), "inference_share": share["share"],
        "shuffled_mb": shuffled, "spilled_mb": spilled,
    }))


if __name__ == "__main__":
    main()
