"""A training corpus from raw documents, stage by stage.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read
again as the next stage's documents: quality classifier, near duplicates, personal data, source
mixing, packing. All but the last return the columns of ``documents``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from zbox.llm import mixing, packing, pii, quality_mil, shingles
from zbox.llm.common import discard, free_name, materialize, read_table
from zbox.llm.components import connected_components
from zbox.llm.queries import PII_KEY, byte_bpe


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier scores 0.3 or more. Trained on the labels of these documents.

    Null and empty texts are one empty passage and are judged like any other; so are very long texts, whole.
    Repeated rows and null ids are judged each. Without labels all documents stay (their score is one half).
    No documents: none."""
    model = quality_mil.train(docs, read_table(spark, sf_dir, "labels"))
    score = free_name(docs, "score")
    return quality_mil.add_score(docs, model, out=score).filter(F.col(score) >= 0.3).drop(score)


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component of near copies (five-word shingles, similarity 0.8): the first by id,
    then by text. Candidates are SimHash links and shared bands (:mod:`zbox.llm.shingles`).

    Only ids and hashes are ranked: the least row of each component is found by partial minima, and
    rows are marked by it. A row that repeats another in id and text goes as well, the first by all other
    columns stays. Null texts are copies of each other, texts without words too; a null id comes before all
    others. No documents: none."""
    key, h = free_name(docs, "_key"), F.xxhash64("text")
    marked = materialize(shingles.add_marks(docs.select(F.struct("doc_id", h.alias("h")).alias(key), "text"), [key]))
    first = [F.first(c).alias(c) for c in ("bands", "fp")]
    classes = materialize(marked.groupBy(F.col(f"{key}.h").alias("node")).agg(F.min(key).alias("least"), *first))
    roots = connected_components(shingles.links(docs, classes.select("node", "bands", "fp")))
    classes = classes.select(F.col("node").alias("of"), "least")
    rooted = classes.join(roots, classes["of"] == roots["node"], "left")
    best = rooted.groupBy(F.coalesce("root", "of").alias("root")).agg(F.min("least").alias("k")).select("k").distinct()
    # plain equality on keys that are never null: the rows are then dealt once for both the join and the ranking
    name = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    i, t, r = (free_name(docs, x) for x in ("_id", "_text", "_rank"))
    best = best.select(name(F.col("k.doc_id")).alias(i), F.col("k.h").alias(t))
    kept = docs.withColumns({i: name(F.col("doc_id")), t: h}).join(best, [i, t], "left_semi")
    rest = [F.col(f"`{c}`") for c, kind in docs.dtypes if c not in ("doc_id", "text") and not kind.startswith("map")]
    one = Window.partitionBy(i, t).orderBy(*rest, F.col("doc_id"))
    return kept.withColumn(r, F.row_number().over(one)).filter(F.col(r) == 1).select(*(F.col(f"`{c}`") for c in docs.columns))


def replace_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with surrogates, and their new lengths.

    Null texts stay null and keep their length as it was; empty ones stay empty; very long ones are read
    whole. Repeated rows are rewritten alike. Null ids are carried. No documents: none."""
    clash = {c: free_name(docs, f"_in_{c}") for c in docs.columns if c.lower() in ("n_entities", "entities")}
    replaced = pii.replace(docs.withColumnsRenamed(clash), PII_KEY)
    n = F.length("text").cast("long")
    replaced = replaced.withColumn("n_chars", F.coalesce(n, F.col("n_chars")))
    return replaced.select(*(F.col(f"`{clash.get(c, c)}`").alias(c) for c in docs.columns))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: none, one or two equal rows.

    A null source is a source of its own; texts without words, null ones too, are taken once. Rows equal in
    id and text are interchangeable: either may get the odd copy. No documents: none."""
    return mixing.take(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row per piece of a document, with its sequence and place.

    Null and empty texts are the end token alone. Repeated rows are packed each. Only texts longer than a
    sequence are cut. No documents: no pieces."""
    return packing.pack(docs, byte_bpe())


STAGES = [
    ("quality classifier", keep_quality),
    ("near duplicates", keep_one_of_near_copies),
    ("personal data", replace_personal_data),
    ("source mixing", mix_sources),
    ("packing", pack_sequences),
]

#: SQL cannot express the classifier, the near copies or the tokens; tests check each stage by brute force or properties.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = read_table(spark, sf_dir, "documents")
    before = None
    for _, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir))
        if before is not None:  # a stage's result is not read again once the next one's is written
            discard(before)
        before = docs
    return STAGES[-1][1](spark, docs, sf_dir)
