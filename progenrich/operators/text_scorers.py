"""Real scorers on text and vectors: lexical rules, containment, fitted classifiers, neighbours."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Scorer

# Fixed word lists of the lexical scorers.
RUDE = ("idiot", "moron", "clown")
STOPS = {"en": ("the", "of", "and", "to", "in"), "fr": ("le", "la", "de", "et", "les"), "de": ("der", "die", "und", "das", "ist"), "es": ("el", "los", "que", "y", "de")}


def extract_features(docs: DataFrame, text: str = "text") -> DataFrame:
    """Text measures as native columns: ``words, other_share, upper_share, mark_share, rude, mean_word``."""
    t = F.col(text)
    n = F.greatest(F.length(t), F.lit(1))
    words = F.regexp_count(t, F.lit(r"[^ \t\n\r]+")).cast("long")
    return docs.select(
        "*", words.alias("words"), (F.length(F.regexp_replace(t, "[A-Za-z]", "")) / n).alias("other_share"), (F.regexp_count(t, F.lit("[A-Z]")) / n).alias("upper_share"),
        (F.regexp_count(t, F.lit(r"[!%*#$&]")) / n).alias("mark_share"), F.lower(t).rlike("(" + "|".join(RUDE) + ")").alias("rude"), (n / F.greatest(words, F.lit(1))).alias("mean_word"),
    )


def hashed_tfidf(docs: DataFrame, text: str = "text", buckets: int = 1 << 18) -> DataFrame:
    """``object_id, bucket, tf, weight``: sparse features, one row for each bucket that a document's words hash to.

    Words are runs without white space, in lower case; ``tf`` is their number, ``weight = tf * ln((1 + N) / (1 + df))`` with
    N documents and df of them in the bucket. Null and empty texts have no rows but count in N. There are at most
    ``buckets`` rows of df, so their join is a broadcast whatever the input; rows of one id are one document.
    """
    words = F.filter(F.split(F.lower(F.col(text)), r"\s+"), lambda x: x != "")
    each = docs.select("object_id", F.explode(words).alias("word"))
    tf = each.groupBy("object_id", F.pmod(F.xxhash64("word"), F.lit(buckets)).cast("int").alias("bucket")).agg(F.count("*").alias("tf"))
    df = tf.groupBy("bucket").agg(F.count("*").alias("df"))
    idf = df.crossJoin(docs.agg(F.count_distinct("object_id").alias("n"))).select("bucket", F.log((1 + F.col("n")) / (1 + F.col("df"))).alias("idf"))
    return tf.join(F.broadcast(idf), "bucket").select("object_id", "bucket", "tf", (F.col("tf") * F.col("idf")).alias("weight"))


FEATURES = ("other_share", "upper_share", "mark_share", "mean_word")


def lexical_toxic(t: Column) -> Column:
    """Probability of rude text by its word list."""
    return F.when(F.lower(t).rlike("(" + "|".join(RUDE) + ")"), 0.95).otherwise(0.05)


def lexical_quality(t: Column) -> Column:
    """Probability of good text from the share of odd marks."""
    share = F.regexp_count(t, F.lit(r"[!%*#$&]")) / F.greatest(F.length(t), F.lit(1))
    return F.greatest(F.lit(0.02), F.least(F.lit(0.98), 1 - 12 * share))


def lexical_lang(t: Column, lang: str) -> Column:
    """Share of the language's common words among those of all languages."""
    low = F.lower(t)
    counts = {k: F.regexp_count(low, F.lit(r"\b(" + "|".join(v) + r")\b")) for k, v in STOPS.items()}
    total = sum((c for c in counts.values()), F.lit(0))
    return (counts[lang] + 0.25) / (total + 1.0)


def containment(docs: DataFrame, items: DataFrame, n: int = 8, rate: int = 1) -> DataFrame:
    """``object_id, prob``: whether a document holds word runs of a benchmark item; 1 in ``rate`` runs is tried.

    Runs are hashed and joined; only matches are gathered, as the most for a document.
    """

    def runs(df: DataFrame, key: str) -> DataFrame:
        words = F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != "")
        w = df.select(key, words.alias("w")).where(F.size("w") >= n)
        each = w.select(key, F.explode(F.sequence(F.lit(1), F.size("w") - n + 1)).alias("i"), "w")
        return each.select(key, F.xxhash64(F.concat_ws(" ", F.slice("w", F.col("i"), F.lit(n)))).alias("h")).where(F.pmod("h", F.lit(rate)) == 0).distinct()

    hits = runs(docs, "object_id").join(runs(items, "item_id").select("h").distinct(), "h").groupBy("object_id").agg(F.count("*").alias("k"))
    return docs.select("object_id").join(hits, "object_id", "left").select("object_id", F.coalesce(F.least(F.lit(1.0), F.col("k") / 5.0), F.lit(0.0)).alias("prob"))


CLASSIFIERS = ("dt", "gnb", "rf", "mlp", "svm", "lr")


def fit_classifier(kind: str, train: DataFrame, features: list[str], label: str, seed: int = 7):
    """A fitted pipeline of assembler and classifier over numeric columns."""
    from pyspark.ml import Pipeline
    from pyspark.ml import classification as c
    from pyspark.ml.feature import StandardScaler, VectorAssembler

    made = {
        "dt": lambda: c.DecisionTreeClassifier(maxDepth=5, seed=seed),
        "gnb": lambda: c.NaiveBayes(modelType="gaussian"),
        "rf": lambda: c.RandomForestClassifier(numTrees=20, maxDepth=5, seed=seed),
        "mlp": lambda: c.MultilayerPerceptronClassifier(layers=[len(features), 8, 2], maxIter=40, seed=seed),
        "svm": lambda: c.LinearSVC(maxIter=20),
        "lr": lambda: c.LogisticRegression(maxIter=30),
    }[kind]()
    made = made.setFeaturesCol("x").setLabelCol(label)
    return Pipeline(stages=[VectorAssembler(inputCols=features, outputCol="raw_x"), StandardScaler(inputCol="raw_x", outputCol="x", withMean=True), made]).fit(train)


def positive(model, df: DataFrame, kind: str) -> DataFrame:
    """``df`` with ``prob``: the probability of label 1; a margin is squashed where there is no probability."""
    from pyspark.ml.functions import vector_to_array

    out = model.transform(df)
    if kind == "svm":
        return out.withColumn("prob", 1 / (1 + F.exp(-vector_to_array("rawPrediction")[1])))
    return out.withColumn("prob", vector_to_array("probability")[1])


def with_ensemble(df: DataFrame, models: dict) -> DataFrame:
    """``df`` with ``prob``, the mean over all models: one pass, each model after the other."""
    for k, m in models.items():
        df = positive(m, df, k).withColumnRenamed("prob", f"p_{k}").drop("raw_x", "x", "rawPrediction", "probability", "prediction")
    return df.withColumn("prob", ensemble([F.col(f"p_{k}") for k in models]))


def ensemble(columns: list[Column]) -> Column:
    return sum(columns[1:], columns[0]) / len(columns)


def knn(train: DataFrame, df: DataFrame, vector: str, label: str, tag, k: int = 5, most: int = 20_000) -> DataFrame:
    """``object_id, prob``: the share of the tag among the k nearest training vectors, over Arrow batches.

    The training matrix is bounded by ``most`` rows and goes to every worker once.
    """
    import numpy as np
    import pyarrow as pa

    rows = train.select("object_id", vector, (F.col(label) == F.lit(tag)).cast("int").alias("y")).orderBy(F.xxhash64("object_id")).limit(most).collect()
    shared = df.sparkSession.sparkContext.broadcast((np.array([r[vector] for r in rows], np.float32), np.array([r["y"] for r in rows], np.float32)))

    def run(batches):
        x, y = shared.value
        norm = (x * x).sum(1)
        for b in batches:
            if not b.num_rows:
                continue
            q = np.stack([np.asarray(v, np.float32) for v in b["v"].to_pylist()])
            near = np.argpartition(norm - 2 * q @ x.T, min(k, len(x)) - 1, axis=1)[:, :k]
            yield pa.RecordBatch.from_arrays([b["object_id"], pa.array(y[near].mean(1).astype(np.float64))], names=["object_id", "prob"])

    return df.select("object_id", F.col(vector).alias("v")).mapInArrow(run, "object_id long, prob double")


#: Fitted scorers of a catalog: kind, cost, and the map that calibrates it (fixed values). The neighbours and the ensemble stand last.
FITTED = (("gnb", 1.0, "isotonic"), ("dt", 2.0, "platt"), ("svm", 4.0, "platt"), ("rf", 10.0, "platt"), ("mlp", 16.0, "platt"), ("knn", 24.0, "platt"))
#: The same with the mean of all fitted models as the dearest scorer.
WITH_ENSEMBLE = (*FITTED, ("ensemble", 40.0, "platt"))


def fitted_scorers(tag_type: str, train: DataFrame, label: str, kinds=FITTED, features=FEATURES) -> tuple[list[Scorer], dict]:
    """Scorers fitted on ``train`` for a type with tags 0 and 1, and the calibration that each asks for.

    Qualities start at one half; ``learning.catalog_with`` sets them from validation objects.
    """
    y = train.withColumn("y", F.col(label).cast("double")).withColumn("vec", F.array(*features))
    models = {k: fit_classifier(k, y, list(features), "y") for k, _, _ in kinds if k not in ("knn", "ensemble")}

    def of_one(payload: DataFrame, kind: str) -> DataFrame:
        """``object_id, prob`` for tag 1."""
        if kind == "knn":
            return knn(y, payload.withColumn("vec", F.array(*features)), "vec", "y", 1.0, 9)
        return positive(models[kind], payload.select("object_id", *features), kind).select("object_id", "prob")

    def ensemble_of(payload: DataFrame) -> DataFrame:
        return with_ensemble(payload.select("object_id", *features), models).select("object_id", "prob")

    def apply_of(kind: str):
        def apply(payload: DataFrame, tag) -> DataFrame:
            out = ensemble_of(payload) if kind == "ensemble" else of_one(payload, kind)
            return out.select("object_id", (F.col("prob") if tag == 1 else 1 - F.col("prob")).alias("prob"))

        return apply

    made = [Scorer(tag_type, n, cost, 0.5, apply=apply_of(kind)) for n, (kind, cost, _) in enumerate(kinds)]
    return made, {(tag_type, n): fit for n, (_, _, fit) in enumerate(kinds)}


def text_catalog_scorers() -> list[Scorer]:
    """Lexical scorers as catalog entries."""
    from .scorers import from_column

    return [
        from_column("Toxic", 0, 1.0, 0.9, lambda tag: lexical_toxic(F.col("text")) if tag == 1 else 1 - lexical_toxic(F.col("text"))),
        from_column("Quality", 0, 1.0, 0.9, lambda tag: lexical_quality(F.col("text")) if tag == 1 else 1 - lexical_quality(F.col("text"))),
        from_column("Lang", 0, 1.0, 0.9, lambda tag: lexical_lang(F.col("text"), tag)),
    ]
