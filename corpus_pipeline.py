"""A corpus pipeline of five stages over ``documents``; each stage is one operator of ``biascut.llm``.

Each function takes (spark, docs, sf_dir), docs being the Parquet table its predecessor left, and
returns a DataFrame; all but the last return the columns of ``documents``, so texts that a stage
changed replace the originals and n_chars follows them.

1. language id: documents without a recognisable language (null or letter-free text) go.
2. line dedup: repeated lines stay only in the first document that holds them.
3. SimHash near-dedup: of each group of near copies (five-word shingles, similarity of 0.8 or more, by
   wide fingerprints) the smallest doc_id stays.
4. suffix-array dedup: byte strings that occur elsewhere go.  Documents stay, emptied ones too.
5. best-fit packing: the rest is packed into sequences; returns pieces and their places.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from biascut.llm import langid, linededup, packing, simhash, suffixdedup
from biascut.llm.common import scratch_path
from biascut.llm.queries import vocabulary

#: SQL cannot express the first and third stage; a test holds run() against a brute force of all five.
ORACLE_SQL = None


def _wrapped(docs: DataFrame) -> DataFrame:
    """The table's rows but for their texts as one column, so that no name meets an operator's own."""
    return docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns if c != "text")).alias("row"), "doc_id", "text")


def _unwrapped(out: DataFrame, columns: list[str], text, changed: bool = True) -> DataFrame:
    """``columns`` from the row and the text; n_chars follows a changed text."""
    put = {"text": text.alias("text")} | ({"n_chars": F.char_length(text).cast("long").alias("n_chars")} if changed else {})
    return out.select(*(put.get(c, F.col("row").getField(c).alias(c)) for c in columns))


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    tagged = langid.identify(_wrapped(docs), langid.training_samples(docs), keep=["row", "text"])
    return _unwrapped(tagged.where(F.col("lang_pred") != langid.UNKNOWN), docs.columns, F.col("text"), changed=False)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _unwrapped(linededup.dedup_lines(_wrapped(docs), keep=["row"]), docs.columns, F.col("kept_text"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    groups = simhash.near_duplicates(docs.select("doc_id", "text"), width=5, radius=simhash.WIDE_RADIUS, bits=simhash.WIDE_BITS, similarity=0.8)
    gone = groups.where(F.col("component_id") != F.col("doc_id")).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def drop_repeated_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = suffixdedup.remove_repeats(_wrapped(docs), keep=["row"], with_text=True)
    return _unwrapped(out, docs.columns, F.col("kept_text"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs, vocabulary("byte_bpe_50k.json"), vocabulary("byte_bpe_50k.tiktoken"))


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", dedup_lines),
    ("simhash_near_dedup", drop_near_copies),
    ("suffix_array_dedup", drop_repeated_strings),
    ("best_fit_packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``, each written to the shared scratch folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        path = scratch_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
