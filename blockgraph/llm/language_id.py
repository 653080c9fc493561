"""Language identification: multinomial naive Bayes over hashed character n-grams.

Learning takes about max_docs_per_lang labelled documents of each language (all, where there are fewer), chosen by a
hash of doc_id and read whole; that bound is the one place where this operator samples. Every language that occurs is
learned. The table of log probabilities has buckets x languages entries, whatever the size of the corpus, and is
broadcast; from TABLE_CELLS entries on more languages share fewer buckets (256 at least). Prediction runs over every whole text: n-grams of a batch become bucket numbers, their rows of the table
are gathered and summed per document in numpy.

Defined results: lang_pred is "und" and score 0.0 for a text that is null or has no letter, and where nothing could be
learned; score is the posterior probability of the language named. Ties go to the alphabetically smaller language.
Repeated rows are predicted each; rows with a null language are not learned from, an empty string is a language like any
other. Very long texts are read whole, by pieces. An empty table gives an empty result; columns of any other name stay
as they are and are not looked at.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ._common import mix

ORDERS = (1, 2, 3)
LAP = max(ORDERS) - 1
BUCKETS = 1 << 15
CHUNK_CHARS = 1 << 18
TABLE_CELLS = 1 << 26


def _bucket_ids(codes: np.ndarray, order: int, buckets: int) -> np.ndarray:
    n = len(codes) - order + 1
    key = np.full(n, order, np.uint64)
    for j in range(order):
        key = key * np.uint64(0x1000193) + codes[j : j + n]
    return (mix(key) & np.uint64(buckets - 1)).astype(np.int64)


class Chunk:
    """Pieces of texts: row of each, code points of all, where each starts, and whether its text goes on after it.

    A long text comes in several pieces, which overlap by the longest order less one; a piece leaves n-grams inside its
    overlap to the next one, so none is lost or counted twice.
    """

    def __init__(self, rows: list[int], parts: list[str], goes_on: list[bool]) -> None:
        self.rows, self.goes_on = rows, goes_on
        self.codes = np.frombuffer("".join(parts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
        self.starts = np.cumsum([0, *map(len, parts)])

    def grams(self, buckets: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Bucket numbers and piece numbers of all n-grams, order by order."""
        piece = np.repeat(np.arange(len(self.rows)), np.diff(self.starts))
        for order in ORDERS:
            if len(self.codes) < order:
                continue
            keep = np.ones(len(self.codes) - order + 1, bool)
            for j in range(1, order):  # n-grams over the end of a piece
                at = self.starts[1:-1] - j
                keep[at[(at >= 0) & (at < len(keep))]] = False
            for k in np.flatnonzero(self.goes_on):
                keep[self.starts[k + 1] - LAP : max(self.starts[k + 1] - order + 1, 0)] = False
            yield _bucket_ids(self.codes, order, buckets)[keep], piece[: len(keep)][keep]


def _chunks(texts: list[str]) -> Iterator[Chunk]:
    """Lower-cased texts, blanks around each, in chunks of bounded size."""
    rows, parts, goes_on, held = [], [], [], 0
    for k, text in enumerate(texts):
        text = f" {text.lower()} "
        for at in range(0, max(1, len(text) - LAP), CHUNK_CHARS):
            parts.append(text[at : at + CHUNK_CHARS + LAP])
            rows.append(k)
            goes_on.append(at + CHUNK_CHARS < len(text) - LAP)
            held += len(parts[-1])
            if held >= CHUNK_CHARS:
                yield Chunk(rows, parts, goes_on)
                rows, parts, goes_on, held = [], [], [], 0
    if rows:
        yield Chunk(rows, parts, goes_on)


def has_letter(text: Column) -> Column:
    return F.coalesce(text.rlike(r"\p{L}"), F.lit(False))


def train(docs: DataFrame, buckets: int = BUCKETS, max_docs_per_lang: int = 4000) -> tuple[list[str], np.ndarray]:
    """Languages in alphabetical order and the table of log probabilities, buckets x languages, float32; buckets is a
    power of two.

    docs(doc_id, text, lang) holds the rows to learn from. What reaches the driver is one count per language and the
    non-empty cells of the table, both bounded by languages x buckets.
    """
    labelled = docs.select(F.col("doc_id").cast("string").alias("k"), "text", "lang").where(F.col("lang").isNotNull() & has_letter(F.col("text")))
    sizes = {r["lang"]: r["n"] for r in docs.where(F.col("lang").isNotNull()).groupBy("lang").agg(F.count("*").alias("n")).collect()}
    langs = sorted(sizes)
    if not langs:
        return [], np.zeros((buckets, 0), np.float32)
    while buckets > 256 and buckets * len(langs) > TABLE_CELLS:
        buckets //= 2
    sampled = [lang for lang in langs if sizes[lang] > max_docs_per_lang]  # the others are taken whole
    drawn = F.lit(True)
    if sampled:
        share = F.create_map(*[F.lit(x) for lang in sampled for x in (lang, max_docs_per_lang / sizes[lang])])
        drawn = F.pmod(F.xxhash64("k"), F.lit(1 << 30)) < F.coalesce(F.try_element_at(share, F.col("lang")), F.lit(1.0)) * (1 << 30)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = {lang: k for k, lang in enumerate(langs)}
        total = np.zeros((len(langs), buckets), np.int64)
        for batch in batches:
            texts, lang = batch.column(0).to_pylist(), [number[x] for x in batch.column(1).to_pylist()]
            for chunk in _chunks(texts):
                cell = np.array([lang[r] for r in chunk.rows], np.int64) * buckets
                for ids, piece in chunk.grams(buckets):
                    total += np.bincount(cell[piece] + ids, minlength=total.size).reshape(total.shape)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total.ravel()[at], pa.int64())], ["cell", "n"])

    counted = labelled.where(drawn).select("text", "lang").mapInArrow(count, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n"))
    found = counted.toArrow()
    counts = np.zeros(len(langs) * buckets)
    counts[found.column("cell").to_numpy()] = found.column("n").to_numpy()
    counts = counts.reshape(len(langs), buckets) + 0.5
    return langs, np.ascontiguousarray(np.log(counts / counts.sum(axis=1, keepdims=True)).T.astype(np.float32))


def _log_odds(texts: list[str], table: np.ndarray, buckets: int) -> np.ndarray:
    """Texts x languages: summed log probabilities of each text's n-grams."""
    sums = np.zeros((len(texts), table.shape[1]))
    for chunk in _chunks(texts):
        part = np.zeros((len(chunk.rows), table.shape[1]))
        for ids, piece in chunk.grams(buckets):
            first = np.flatnonzero(np.diff(piece, prepend=-1))
            if len(first):
                part[piece[first]] += np.add.reduceat(table[ids], first, axis=0, dtype=np.float64)
        np.add.at(sums, chunk.rows, part)
    return sums


def with_language(spark: SparkSession, docs: DataFrame, model: tuple[list[str], np.ndarray]) -> DataFrame:
    """row (a struct of all columns of docs) and said(lang, score); only the text travels to Python."""
    langs, weights = model
    shared, buckets = spark.sparkContext.broadcast(weights), len(weights)

    @F.pandas_udf("struct<lang:string,score:double>")
    def named(text: pd.Series) -> pd.DataFrame:
        if not langs:
            return pd.DataFrame({"lang": ["und"] * len(text), "score": [0.0] * len(text)})
        sums = _log_odds([t if isinstance(t, str) else "" for t in text], shared.value, buckets)
        odds = np.exp(sums - sums.max(axis=1, keepdims=True)).sum(axis=1)
        return pd.DataFrame({"lang": [langs[k] for k in sums.argmax(axis=1)], "score": 1.0 / odds})

    none = F.struct(F.lit("und").alias("lang"), F.lit(0.0).alias("score"))
    rows = docs.select(F.struct(*docs.columns).alias("row"))
    return rows.withColumn("said", F.when(has_letter(F.col("row.text")), named("row.text")).otherwise(none))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def identify(spark: SparkSession, docs: DataFrame, max_docs_per_lang: int = 4000) -> DataFrame:
    """Learn from the rows that are not held out; predict all. doc_id, held_out, lang_pred, score."""
    model = train(docs.where(~held_out(F.col("doc_id"))), max_docs_per_lang=max_docs_per_lang)
    said = with_language(spark, docs.select("doc_id", "text"), model)
    return said.select(F.col("row.doc_id").cast("long").alias("doc_id"), held_out(F.col("row.doc_id")).alias("held_out"), F.col("said.lang").alias("lang_pred"), F.col("said.score").alias("score"))


def confident(spark: SparkSession, docs: DataFrame, least: float = 0.5) -> DataFrame:
    """The rows of docs whose language is recognised with a score of at least `least`, unchanged.

    Rows with a null doc_id go too.
    """
    model = train(docs.where(~held_out(F.col("doc_id"))))
    said = with_language(spark, docs.where(F.col("doc_id").isNotNull()), model)
    return said.where((F.col("said.lang") != "und") & (F.col("said.score") >= least)).select("row.*")
