"""A corpus pipeline of five stages over ``documents``, each of an operator of ``bspflow.llm``.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again as the next
one's ``docs``; all but the last keep the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bspflow.llm import langid, pii
from bspflow.llm.common import WORD_PATTERN, materialize
from bspflow.llm.mixing import mix_sources
from bspflow.llm.queries import SAMPLES, piece_model
from bspflow.llm.simhash import near_duplicate_components
from bspflow.llm.spiece import sample_segmentations

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Train on the labelled documents that aren't held out; documents without a language (``und``) go.

    If no document tells of a language, those without a letter go.
    """
    model = langid.train(docs.where(~langid.held_out(F.col("doc_id"))).select("doc_id", "text", "lang"))
    if not model.languages:
        return docs.where(F.col("text").rlike(r"\p{L}")).select(*COLUMNS)
    return langid.predict(docs, model).where(F.col("lang_pred") != langid.UNKNOWN).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of linked fingerprints one row stays: the smallest doc_id's.

    Rows are told apart by id and text: one that shares its id with a copy stays if its own text is no copy.  Rows that
    repeat both become one (the least by lang, source, n_chars); of two texts of one id in a component one stays; rows
    without an id come after all others, so one of them stays only where its component has no id.
    """
    told = F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), F.coalesce(F.concat(F.lit(" :"), F.col("text")), F.lit(" ")))
    keyed = docs.select(*COLUMNS).withColumn("row_key", F.unhex(F.md5(told.cast("binary"))))
    found = near_duplicate_components(keyed, row_key="row_key")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row_key")).alias("first")
    stay = found.groupBy("component").agg(first).select("first.row_key")
    # repeats fold before the texts move; the ids to keep grow with the corpus, so they aren't broadcast at any size
    rows = keyed.groupBy("row_key").agg(F.min(F.struct("doc_id", "lang", "source", "n_chars", "text")).alias("row")).select("row_key", "row.*")
    return rows.join(stay.hint("merge"), "row_key", "left_semi").select(*COLUMNS)


def redact_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans of personal data become their kind in brackets; n_chars follows the text."""
    return pii.redact(docs.select(*COLUMNS)).withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; the one on a source's cut gives its leading words once more."""
    # the texts go with their rows through the prefix sums: they move once at every size, and rows sharing an id stay apart
    rows = mix_sources(docs.select(*COLUMNS), carry=("text", "lang", "n_chars")).where("taken > 0")
    words = F.array_join(F.slice(F.regexp_extract_all("text", F.lit(WORD_PATTERN), F.lit(0)), 1, F.col("cut").cast("int")), " ")
    rows = rows.withColumn("times", F.expr("cast(epochs + if(cut = size, 1, 0) as int)")).withColumn("lead", F.when((F.col("cut") > 0) & (F.col("cut") < F.col("size")), words))
    again = F.expr("concat(array_repeat(false, times), if(lead IS NOT NULL, array(true), array()))")
    rows = rows.withColumn("is_lead", F.explode(again)).withColumn("text", F.when(F.col("is_lead"), F.col("lead")).otherwise(F.col("text")))
    return rows.withColumn("n_chars", F.when(F.col("is_lead"), F.char_length("text").cast("long")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sampled segmentations of every text as piece numbers."""
    return sample_segmentations(docs, piece_model(), k=SAMPLES, seed=11)


STAGES = [("language", identify_language), ("near copies", drop_near_copies), ("personal data", redact_personal_data), ("mix", mix), ("pieces", encode)]

#: Fingerprints, the classifier, the field and the sampled segmentations have no SQL form; tests/llm holds the
#: pipeline against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
