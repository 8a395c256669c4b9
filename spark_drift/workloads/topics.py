"""A stream of texts in yearly batches, in which languages and their topics enter one after another."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.functions import text
from spark_drift.functions.expressions import hash_unit
from spark_drift.functions.numeric import OnlineConfig
from spark_drift.operators import degree, ensemble, mixture, views
from spark_drift.operators.ensemble import Adaptation
from spark_drift.operators.online import Stepper
from spark_drift.plans.lineage import cut
from spark_drift.sources.tables import read

#: first pseudo-year in which a language appears; in the replay each beyond the first enters within a block of years
ENTERS = {"en": 2000, "fr": 2005, "de": 2010, "es": 2014}
REPLAY_ENTERS = {"en": 2000, "fr": 2005, "de": 2012, "es": 2016}
DIMS = [f"s{k}" for k in range(10)]
TERMS, TOPICS = 5000, 10
BASE = 2003  # last year of the initial training rows
BLOCKS = [(2004, 2007), (2008, 2011), (2012, 2015), (2016, 2018), (2019, 2019)]


def pseudo_years(docs: DataFrame, enters: dict[str, int] = ENTERS) -> DataFrame:
    """``doc_id, year, lang, text``: a year from the id's digest, between the language's
    entry and 2019."""
    entry = F.lit(2000)
    for lang, year in enters.items():
        entry = F.when(F.col("lang") == lang, year).otherwise(entry)
    year = entry + F.floor(hash_unit(F.concat(F.lit("year:"), F.col("doc_id").cast("string"))) * (F.lit(2019.999999) - entry))
    return docs.select("doc_id", year.cast("int").alias("year"), "lang", "text")


def reduced(spark: SparkSession, sf_dir: str, terms: int = TERMS, topics: int = TOPICS, rounds: int = 20) -> DataFrame:
    """``doc_id, year, lang, label, train, s0..s9``: the most frequent terms' weights in ten dimensions, the
    dominant of ten topics as label, and whether the document is one of the 60 % to train on."""
    docs = pseudo_years(read(spark, sf_dir, "documents"), REPLAY_ENTERS)
    rows = text.reduce(text.vectors(docs, terms), "tfidf", 10)
    rows = text.topics(rows, topics, rounds=rounds)
    train = hash_unit(F.concat(F.lit("split:"), F.col("doc_id").cast("string"))) < 0.6
    features = [F.col("features")[k].alias(c) for k, c in enumerate(DIMS)]
    return rows.select("doc_id", "year", "lang", F.col("topic").alias("label"), train.alias("train"), *features)


REPLAY = (
    "years string, year int, alarm boolean, action string, components int, births int, degree_before double, degree_after double, "
    "accuracy_before double, accuracy_after double, density_change double, rows long"
)


def _accuracy(models: dict, weights: dict[str, float], rows: DataFrame) -> float | None:
    spark = rows.sparkSession
    w = spark.createDataFrame([(n, float(weights[n])) for n in models], "learner string, weight double")
    votes = ensemble.vote(ensemble.predict(models, rows.select("doc_id", *DIMS), ["doc_id"]), w, ["doc_id"])
    scored = votes.join(rows.select("doc_id", "label"), "doc_id").withColumn("j", F.lit(0))
    found = ensemble.accuracy(scored, ["j"]).first()
    return None if found is None else float(found["accuracy"])


def _weights(models: dict, seen: DataFrame, beta: float = 0.9) -> dict[str, float]:
    """The weight policy: beta to the power of each learner's mistakes per ten labelled rows seen so far
    (training rows, never test rows), normalised."""
    predictions = ensemble.predict(models, seen.select("doc_id", "label", *DIMS), ["doc_id", "label"])
    wrong = predictions.groupBy("learner").agg(F.avg((F.col("pred") != F.col("label")).cast("double")).alias("wrong")).collect()
    raw = {r["learner"]: beta ** (100 * r["wrong"]) for r in wrong}
    total = sum(raw.values()) or 1.0
    return {n: raw.get(n, 0.0) / total for n in models}


def _density_change(rows: DataFrame, ref: DataFrame, component: int) -> float:
    """Half the summed cell differences between a batch and the training rows in one component."""
    side = lambda df: df.where(F.col("comp_id") == component).select(F.col(DIMS[0]).alias("x"), F.col(DIMS[1]).alias("y"))
    a, b = side(ref), side(rows)
    if a.isEmpty() or b.isEmpty():
        return 1.0
    bounds = tuple(a.unionByName(b).agg(F.min("x"), F.max("x"), F.min("y"), F.max("y")).first())
    grid = lambda df: views.grid(df, "x", "y", bounds, 4)
    return float(views.density_diff(grid(a), grid(b)).agg(F.sum(F.abs("diff")) / 2).first()[0] or 0.0)


def replay(spark: SparkSession, sf_dir: str, threshold: float = 0.1, cfg: OnlineConfig | None = None) -> DataFrame:
    """One row per block of years: a base model on the first four years, then years arrive one by one.

    Each year is one distributed step of the mixture. The degree of the rows of the block so far decides: at
    ``threshold`` or more the script adapts once in the block, with the components that were born in it or, where
    there are none, the one whose density changed most. It trains one learner per chosen component on its training
    rows (the block's as well as earlier ones), weighs learners by their mistakes, and takes all learners' rows as
    reference. Blocks below the threshold pass without action. Accuracy is that of test rows of the block.
    """
    rows = cut(reduced(spark, sf_dir))
    cfg = cfg or OnlineConfig(min_pool=max(30, rows.where(f"year <= {BASE}").count() // 4))
    base = cut(rows.where(f"train and year <= {BASE}"))
    models, weights = {"base": ensemble.train_learner(base, DIMS, kind="svm")}, {"base": 1.0}
    trained = {"base": base.select("doc_id")}
    stepper = Stepper(base, DIMS, cfg)
    analyst = Adaptation(learners=(("base", tuple(int(i) for i in stepper.mix.ids)),))
    out = []
    for low, high in BLOCKS:
        born, done = set(), None
        old = set(stepper.mix.ids.tolist())
        for year in range(low, high + 1):
            if stepper.step(rows.where(F.col("year") == year).select(*DIMS), float(year)) is None:
                continue
            born |= set(stepper.mix.ids.tolist()) - old
            block = rows.where(F.col("year").between(low, year))
            marked = cut(mixture.assign(block, DIMS, stepper.mix).withColumn("t", F.lit(0)))
            ref = cut(mixture.assign(rows.join(_union(trained), "doc_id", "left_semi"), DIMS, stepper.mix))
            parts = degree.of_batch(ref, marked, "t", DIMS)
            before = float(parts["part"].sum())
            done = (year, before, marked, ref, parts)
            if before >= threshold:
                break
        if done is None:
            continue
        year, before, marked, ref, parts = done
        test = rows.where(F.col("year").between(low, high) & ~F.col("train"))
        acc = _accuracy(models, weights, test)
        alarm, action, after, acc_after, change = before >= threshold, "", before, acc, None
        if alarm:
            top = parts.sort_values(["part", "comp_id"], ascending=[False, True])
            chosen = [int(c) for c in top["comp_id"] if int(c) in born]
            if not chosen:
                looked = [(int(c), _density_change(marked, ref, int(c))) for c in top["comp_id"].head(3)]
                best, change = max(looked, key=lambda p: p[1])
                chosen = [best]
            action = "new components" if born & set(chosen) else "density"
            # all rows up to the end of the block count as arrived when the analyst acts
            seen = cut(mixture.assign(rows.where((F.col("year") <= high) & F.col("train")), DIMS, stepper.mix))
            for c in chosen:
                name = f"learner_{len(models)}"
                own = seen.where(F.col("comp_id") == c)
                if own.select("label").distinct().count() < 2:
                    own = seen.where(F.col("year").between(low, high))
                models[name], trained[name] = ensemble.train_learner(own, DIMS, kind="svm"), own.select("doc_id")
                analyst = Adaptation((*analyst.learners, (name, (c,))), (*analyst.actions, (float(year), "add", name)))
            weights = _weights(models, seen.where(F.col("year").between(low, high)))
            ref = cut(mixture.assign(rows.join(_union(trained), "doc_id", "left_semi"), DIMS, stepper.mix))
            after = float(degree.of_batch(ref, marked, "t", DIMS)["part"].sum())
            acc_after = _accuracy(models, weights, test)
        out.append((f"{low}-{high}", year, bool(alarm), action, len(stepper.mix.ids), len(born), before, after, acc, acc_after, change, marked.count()))
    return spark.createDataFrame(out, REPLAY)


def _union(trained: dict[str, DataFrame]) -> DataFrame:
    """Ids of all learners' training rows."""
    out = None
    for ids in trained.values():
        out = ids if out is None else out.union(ids)
    return out.distinct()
