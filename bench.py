"""Headline queries, timed. Prints one line of JSON.

BENCH_SF_DIR: folder of the tables; BENCH_CPUS: cores. Counts printed beside the seconds are the ones the reference reports
for its own data: sizes by depth and threshold, scans, widths.
"""

from __future__ import annotations

import json
import os
import tempfile
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from supportbounds import queries
from supportbounds.plans import derive, measures
from supportbounds.plans.levelwise import mine_all_fpgrowth, mine_all_levelwise, mine_nonderivable

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "6g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", f"file://{tempfile.mkdtemp(prefix='supportbounds-bench-')}")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    facts: dict[str, object] = {}

    def timed(name: str, run):
        began = time.time()
        out = run()
        seconds[name] = round(time.time() - began, 3)
        return out

    db = timed("encode_words_12", lambda: queries.words(spark, SF_DIR, 12))
    facts["n_baskets"] = db.n_baskets
    s = int(db.n_baskets * 0.3)
    facts["min_support"] = s
    kept = {}
    for depth in (0, 1, 2, 3, 4, 5):
        mine = (lambda: mine_all_levelwise(db, s)) if depth == 0 else (lambda d=depth: mine_nonderivable(db, s, max_depth=d))
        run = timed(f"mine_depth{depth}", mine)
        kept[depth] = run.sets.count()
        if depth == 0:
            facts["all_frequent"], facts["scans_all"] = kept[0], run.scans
        if depth in (1, 2, 3):
            derived = timed(f"derive_depth{depth}", lambda r=run: derive.all_frequent(r).sets)
            facts[f"same_as_all_depth{depth}"] = derived.count() == kept[0]
    facts["kept_by_depth"], facts["scans_kept"] = kept, run.scans
    facts["ratio"] = round(kept[5] / max(1, kept[0]), 4)
    facts["mean_width_by_size"] = {r.k: round(r.mean_width, 3) for r in measures.width_by_size(run).orderBy("k").collect()}
    timed("all_frequent_fpgrowth", lambda: mine_all_fpgrowth(db, s).count())
    for name in ("nonderivable_order_part", "nonderivable_order_attr", "nonderivable_userday", "pair_supports", "triple_supports"):
        timed(name, lambda n=name: queries.QUERIES[n](spark, SF_DIR).agg(F.count("*")).collect())
    try:
        from supportbounds.llm import queries as corpus
    except ImportError:
        corpus = None
    for name, query in corpus.QUERIES.items() if corpus else ():
        timed(name, lambda q=query: q(spark, SF_DIR).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(SF_DIR.rstrip("/")), "facts": facts}))
    spark.stop()


if __name__ == "__main__":
    main()
