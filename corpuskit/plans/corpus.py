"""The corpus phases composed: merge and exact dedup, clean, language, near dedup, quality.

Cleaned text is written once, before the length filter; later phases pass slim id sets, and a final semi-join applies
them. Every stage lies in the shared folder, so all reports read one run.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property, reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.config import DEFAULT, Config
from corpuskit.functions.text import word_count
from corpuskit.operators import clean, exact, lid, neardup, quality, release
from corpuskit.session import staged
from corpuskit.sources import with_roles

STAGES = ("raw", "p1", "p2", "p3", "p4", "p5")
#: (doc_id, label, prob) of documents with text in `clean`.
Identifier = Callable[[DataFrame], DataFrame]


def gold(docs: DataFrame) -> DataFrame:
    """The identifier that reads the label a document came with."""
    return docs.select("doc_id", F.col("lang").alias("label"), F.lit(1.0).alias("prob"))


def profile_identifier(training: DataFrame, label: str = "lang", text: str = "text") -> Identifier:
    """The profile model, trained on labelled documents."""
    return lid.identifier(staged(lid.train_profile(training, label, text=text), "profile"))


def matching(docs: DataFrame, ids: DataFrame, how: str = "left_semi") -> DataFrame:
    """The rows of docs whose doc_id is among ids (left_anti: is not); nulls meet nulls."""
    named = ids.select(F.col("doc_id").alias("__id"))
    return docs.join(named, docs["doc_id"].eqNullSafe(named["__id"]), how)


class CorpusRun:
    """One run over docs(doc_id, source, text, lang). `skip` leaves out phases 1 to 5 by number.

    identify: the language identifier of phase 3; unless given, the profile model trained on the labelled documents of
    even doc_id that phase 1 leaves. After phase 1 rows that share a doc_id, or have none, are one document: they stay or go together.
    """

    def __init__(self, docs: DataFrame, config: Config = DEFAULT, identify: Identifier | None = None, skip: tuple[int, ...] = (), base: str = "xx"):
        self.config, self.skip, self.base = config, skip, base
        self.docs, self.raw = docs, with_roles(docs, config)
        if identify:
            self.identify = identify

    @cached_property
    def identify(self) -> Identifier:
        return profile_identifier(self.unique.filter("doc_id % 2 = 0"))

    def without(self, phase: int) -> CorpusRun:
        """A run that leaves a phase out and shares the stages before it with this one."""
        identify = self.identify if phase > 1 else self.__dict__.get("identify")
        other = CorpusRun(self.docs, self.config, identify, (*self.skip, phase), self.base)
        for name, of in (("unique", 1), ("worded", 1), ("cleaned", 2), ("predicted", 3), ("p3_ids", 3), ("near", 4), ("clusters", 4), ("p4_ids", 4), ("scored", 5)):
            if of < phase:
                other.__dict__[name] = getattr(self, name)
        return other

    @cached_property
    def unique(self) -> DataFrame:
        return self.raw if 1 in self.skip else exact.drop_exact(self.raw, self.config.key_mode)

    @cached_property
    def worded(self) -> DataFrame:
        """What phase 1 leaves, with clean text, repairs and n_words, before the length filter."""
        return staged(clean.min_words(clean.normalize(self.unique, self.config), 0), "clean")

    @cached_property
    def cleaned(self) -> DataFrame:
        """Survivors of phase 2 with clean text, repairs and n_words."""
        return self.worded if 2 in self.skip else self.worded.filter(F.col("n_words") >= self.config.min_words)

    @cached_property
    def predicted(self) -> DataFrame:
        return staged(self.identify(self.cleaned), "predicted")

    @cached_property
    def p3_ids(self) -> DataFrame:
        if 3 in self.skip:
            return self.cleaned.select("doc_id")
        return staged(lid.verify(self.predicted, self.config.target, self.config.lid_min_probability).select("doc_id"), "p3")

    @cached_property
    def p3(self) -> DataFrame:
        return self.cleaned if 3 in self.skip else matching(self.cleaned, self.p3_ids)

    @cached_property
    def near(self) -> neardup.NearDuplicates:
        c = self.config
        return neardup.NearDuplicates(self.p3, c.shingle_n, c.k, c.bands, c.rows, c.tau, c.seed, self.base)

    @cached_property
    def clusters(self) -> DataFrame:
        return staged(self.near.clusters(), "clusters")

    @cached_property
    def p4_ids(self) -> DataFrame:
        if 4 in self.skip:
            return self.p3_ids
        return staged(matching(self.p3_ids, neardup.losers(self.p3, self.clusters), "left_anti"), "p4")

    @cached_property
    def p4(self) -> DataFrame:
        return matching(self.cleaned, self.p4_ids)

    @cached_property
    def seed(self) -> DataFrame:
        sources = [s for s, role in self.config.roles if role == "seed"]
        return reduce(DataFrame.union, (quality.seed_docs(self.p4, s, self.config.seed_min_words) for s in sources))

    @cached_property
    def scored(self) -> DataFrame:
        return staged(quality.coverage(self.p4, self.seed, self.config.char_n), "scored")

    @cached_property
    def p5_ids(self) -> DataFrame:
        if 5 in self.skip:
            return self.p4_ids
        return staged(quality.drop_bottom(self.scored, self.config.drop_percent).select("doc_id"), "p5")

    @cached_property
    def corpus(self) -> DataFrame:
        return matching(self.cleaned, self.p5_ids)

    @cached_property
    def released(self) -> DataFrame:
        return release.split(self.corpus, self.config.split_percent, "exact", self.config.seed)

    def stage_rows(self) -> DataFrame:
        """(stage, doc_id, source, role, n_words) of every document at every stage."""
        c = ["doc_id", "source", "role"]
        words = F.size(F.filter(F.split(F.col("text"), "[ \\t\\n\\r\\f\\x0B]+"), lambda w: w != "")).cast("long")
        parts = [self.raw.select(F.lit("raw").alias("stage"), *c, words.alias("n_words")), self.unique.select(F.lit("p1").alias("stage"), *c, words.alias("n_words"))]
        for name, rows in (("p2", self.cleaned), ("p3", self.p3), ("p4", self.p4), ("p5", self.corpus)):
            parts.append(rows.select(F.lit(name).alias("stage"), *c, "n_words"))
        return reduce(DataFrame.union, parts)


def retention(stages: DataFrame) -> DataFrame:
    """(stage, n_docs, n_words, cumulative_pct, step_drop_pct) from stage_rows()."""
    return _retention(stages, [])


def retention_by_source(stages: DataFrame, by: str = "role") -> DataFrame:
    return _retention(stages, [by])


def _retention(stages: DataFrame, by: list[str]) -> DataFrame:
    order = F.array_position(F.array(*(F.lit(s) for s in STAGES)), F.col("stage"))
    counts = stages.groupBy(*by, "stage").agg(F.count("*").alias("n_docs"), F.sum("n_words").alias("n_words"))
    w = Window.partitionBy(*(by or [F.lit(0)])).orderBy(order)
    first, before = F.first("n_docs").over(w), F.lag("n_docs").over(w)
    return counts.withColumns({"cumulative_pct": F.round(100 * F.col("n_docs") / first, 4), "step_drop_pct": F.round(100 * (1 - F.col("n_docs") / before), 4)})


def composition(docs: DataFrame, by: str = "role") -> DataFrame:
    counts = docs.groupBy(by).agg(F.count("*").alias("kept_docs"))
    total = docs.agg(F.count("*").alias("all_docs"))
    return counts.crossJoin(F.broadcast(total)).select(by, "kept_docs", F.round(F.col("kept_docs") / F.col("all_docs"), 6).alias("fraction"))


def leakage(run: CorpusRun) -> DataFrame:
    """Documents that phase 3 drops, by predicted label."""
    gone = matching(run.predicted, run.p3_ids, "left_anti")
    counts = gone.groupBy("label").agg(F.count("*").alias("n_docs"))
    return counts.crossJoin(F.broadcast(gone.agg(F.count("*").alias("n")))).select("label", "n_docs", F.round(F.col("n_docs") / F.col("n"), 6).alias("share"))


def drop_by_source(before: DataFrame, after: DataFrame, by: str = "role") -> DataFrame:
    kept = before.select("doc_id", by).join(after.select("doc_id", F.lit(1).alias("kept")), "doc_id", "left")
    n, gone = F.count("*"), F.count("*") - F.count("kept")
    return kept.groupBy(by).agg(n.alias("n_docs"), gone.alias("n_dropped"), F.round(gone / n, 6).alias("drop_rate"))


def variety_counts(tagged: DataFrame, varieties: list[str], column: str = "variety") -> DataFrame:
    """Documents of each variety, the absent ones with 0."""
    spark = tagged.sparkSession
    asked = spark.createDataFrame([(v,) for v in varieties], f"{column} string")
    counts = tagged.groupBy(column).agg(F.count("*").alias("n"))
    return asked.join(counts, column, "left").select(column, F.coalesce("n", F.lit(0)).cast("long").alias("n_docs"))


def inventory(docs: DataFrame) -> DataFrame:
    """Documents, approximate tokens and bytes of each source, and in all (null source)."""
    words = F.size(F.filter(F.split(F.col("text"), "[ \\t\\n\\r\\f\\x0B]+"), lambda w: w != "")).cast("long")
    return docs.select("source", words.alias("w"), F.octet_length("text").cast("long").alias("b")).rollup("source").agg(F.count("*").alias("n_docs"), F.sum("w").alias("n_tokens"), F.sum("b").alias("n_bytes"))


def defects(run: CorpusRun, role: str = "A") -> DataFrame:
    """Defect rates of one source family: exact copies, repaired documents, near copies among its exact-unique documents."""
    raw, own = run.raw.filter(F.col("role") == role), run.unique.filter(F.col("role") == role)
    n_raw, n_own = raw.count(), own.count()
    n_within = exact.drop_exact(raw, run.config.key_mode).count()
    survivors = run.cleaned.filter(F.col("role") == role)
    n_survivors, n_repaired = survivors.count(), survivors.filter("repairs.repaired").count()
    c = run.config
    near = neardup.NearDuplicates(clean.normalize(own, c), c.shingle_n, c.k, c.bands, c.rows, c.tau, c.seed, run.base)
    stats = neardup.cluster_stats(near.clusters()).first()
    part = lambda a, b: round(a / b, 6) if b else 0.0
    rows = [
        ("exact_attributed", n_raw, n_raw - n_own, part(n_raw - n_own, n_raw)),
        ("exact_within", n_raw, n_raw - n_within, part(n_raw - n_within, n_raw)),
        ("repaired_among_survivors", n_survivors, n_repaired, part(n_repaired, n_survivors)),
        ("near_among_exact_unique", n_own, stats["n_removed"], part(stats["n_removed"], n_own)),
    ]
    return run.raw.sparkSession.createDataFrame(rows, "defect string, n_of long, n_defect long, rate double")


def audit_sample(docs: DataFrame, n: int = 20, seed: int = 0) -> DataFrame:
    """A seeded sample: the n documents with the least hash."""
    return docs.withColumn("draw", F.md5(F.concat(F.lit(f"audit|{seed}|"), F.col("doc_id").cast("string")))).orderBy("draw", "doc_id").limit(n)


def check_definition(docs: DataFrame, predicted: DataFrame, scored: DataFrame, target: str, tau: float, floor: float, text: str = "clean") -> DataFrame:
    """Violations of purity, novelty and quality in a finished corpus. Novelty is exact, by the prefix join."""
    ids = docs.select("doc_id")
    impure = ids.join(predicted, "doc_id").filter(~F.col("label").eqNullSafe(F.lit(target))).agg(F.count("*").alias("n"))
    sets = neardup.hashed(neardup.shingles(docs, text=text), "xx")
    twins = neardup.prefix_join(sets, tau).agg(F.count("*").alias("n"))
    poor = ids.join(scored, "doc_id").filter(F.col("coverage") < floor).agg(F.count("*").alias("n"))
    named = [df.select(F.lit(name).alias("property"), F.col("n").alias("n_violations")) for name, df in (("purity", impure), ("novelty", twins), ("quality", poor))]
    return reduce(DataFrame.union, named)


def words_in(docs: DataFrame, text: str = "clean") -> DataFrame:
    return docs.agg(F.sum(word_count(F.col(text))).alias("n_words"))
