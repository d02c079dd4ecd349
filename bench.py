"""Time the headline queries and phases; print one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

os.environ["PYTHONPATH"] = f"{os.path.dirname(os.path.abspath(__file__))}:{os.environ.get('PYTHONPATH', '')}"

from pyspark.sql import DataFrame, SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402


def session() -> SparkSession:
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.files.maxPartitionBytes", "2m")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(make) -> tuple[float, object]:
    began = time.time()
    got = make()
    if isinstance(got, DataFrame):
        got.write.format("noop").mode("overwrite").save()
    return round(time.time() - began, 3), got


#: Published documents per second, of one laptop with 12 cores on 1.37 million documents.
PUBLISHED = {"phase1_exact_dedup": 16_531, "phase2_clean": 597, "phase3_identify": 1_286, "phase4_near_dedup": 3_593, "phase5_quality": 3_031}


def phases(docs: DataFrame, vocab: int) -> tuple[dict[str, float], dict[str, int]]:
    """Seconds of each phase of a corpus run, and the documents it took. Every phase reads all that the one before kept."""
    from corpuskit.operators import tokenizer
    from corpuskit.plans.corpus import CorpusRun

    run, seconds, taken = CorpusRun(docs), {}, {"phase1_exact_dedup": docs.count()}
    seconds["phase1_exact_dedup"], _ = timed(lambda: run.unique)
    seconds["phase2_clean"], _ = timed(lambda: run.cleaned.select("doc_id"))
    seconds["phase3_train_profile"], _ = timed(lambda: run.identify)
    seconds["phase3_identify"], _ = timed(lambda: run.p3_ids)
    seconds["phase4_near_dedup"], _ = timed(lambda: run.p4_ids)
    seconds["phase5_quality"], _ = timed(lambda: run.p5_ids)
    seconds["phase6_split_tokenizer"], _ = timed(lambda: tokenizer.train(run.released.filter("split = 'train'"), vocab))
    taken |= {"phase2_clean": run.unique.count(), "phase3_identify": run.cleaned.count(), "phase4_near_dedup": run.p3_ids.count(), "phase5_quality": run.p4_ids.count(), "final": run.p5_ids.count()}
    return seconds, taken


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    vocab = int(os.environ.get("BENCH_VOCAB", "16000"))
    spark = session()
    from corpuskit.session import scratch

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    n = docs.count()
    docs = docs.repartition(max(8, n // 1000), F.xxhash64("doc_id"))
    # a run of a minute is half start-up: the same phases over the same table twice, both told, the second counted
    with scratch(spark):
        first, _ = phases(docs, vocab)
    seconds, taken = phases(docs, vocab)
    rates = {k: round(taken[k] / seconds[k]) for k in PUBLISHED}
    try:
        from corpuskit.llm.queries import queries
    except ImportError:
        queries = dict
    for name, query in queries().items():
        seconds[name], _ = timed(lambda q=query: q(spark, sf))
    told = {"first_run": first, "docs_per_sec": rates, "docs_per_sec_published": PUBLISHED, "docs": taken, "vocab": vocab}
    print(json.dumps({"metric": "total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, **told, "sf": os.path.basename(sf.rstrip("/"))}))
    sys.stdout.flush()
    spark.stop()


if __name__ == "__main__":
    main()
