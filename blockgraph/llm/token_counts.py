"""Token counts of whole texts: an Arrow function that returns lengths only.

Batches are regrouped by bytes, so one worker never holds much text beside its Arrow batch, and a long text is
split where no token of the vocabulary can cross: before a single space that follows a character which is neither a
space nor the space mark. Pieces with a space mark after another character would break that rule, so the vocabulary
is searched for one when the model is loaded; if there is any, texts stay in one part.

Defined results: a null text counts as empty (0 bytes, 0 tokens); a null doc_id stays null; repeated rows are counted
each; an empty table gives an empty result; further columns of the input, whatever their names, are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BATCH_BYTES = 1 << 20
PART_CHARS = 1 << 16
SPACE_MARK = "▁"
_SAFE = re.compile(rf"(?<=[^ {SPACE_MARK}]) (?=[^ {SPACE_MARK}])")
_loaded: dict = {}


def default_model(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _counter(model: str):
    """The encoder of a worker, and whether its texts may be split."""
    if model not in _loaded:
        if model.endswith(".json"):
            from tokenizers import Tokenizer

            tokenizer = Tokenizer.from_file(model)
            _loaded[model] = (lambda texts: [len(e.ids) for e in tokenizer.encode_batch(texts, add_special_tokens=False)]), False
        else:
            import sentencepiece

            pieces = sentencepiece.SentencePieceProcessor(model_file=model)
            crossing = any(SPACE_MARK in pieces.id_to_piece(i).lstrip(SPACE_MARK) for i in range(pieces.get_piece_size()))
            plain = [len(x) for x in pieces.encode(["a b", "b", " b"], num_threads=1)]
            splits = not crossing and plain[0] == len(pieces.encode("a")) + plain[1] and plain[2] > plain[1]
            _loaded[model] = (lambda texts: [len(x) for x in pieces.encode(texts, num_threads=1)]), splits
    return _loaded[model]


def safe_parts(text: str, limit: int = PART_CHARS) -> list[str]:
    """Parts of at least limit characters (the last may be shorter) whose token counts add up to the text's."""
    parts, start = [], 0
    while len(text) - start > limit:
        cut = _SAFE.search(text, start + limit)
        if cut is None:
            break
        parts.append(text[start : cut.start()])
        start = cut.end()  # the encoder puts a space mark before each part: this space
    parts.append(text[start:])
    return parts


def count_texts(texts: list[str], model: str, batch_bytes: int = BATCH_BYTES) -> list[int]:
    encode, splits = _counter(model)
    counts, group, owners, held = [0] * len(texts), [], [], 0

    def flush() -> None:
        for owner, n in zip(owners, encode(group), strict=True):
            counts[owner] += n

    for k, text in enumerate(texts):
        for part in safe_parts(text) if splits else [text]:
            size = len(part) if part.isascii() else len(part.encode())
            if group and held + size > batch_bytes:
                flush()
                group, owners, held = [], [], 0
            group.append(part)
            owners.append(k)
            held += size
    if group:
        flush()
    return counts


def token_counts(docs: DataFrame, model: str | None = None, limit: int = 4096) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit of every row of docs(doc_id, text)."""
    model = model or default_model()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts = []
            for at in range(0, batch.num_rows, 128):  # few rows at a time become Python objects
                counts += count_texts([t or "" for t in batch.column(1).slice(at, 128).to_pylist()], model)
            counts = pa.array(counts, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), counts], ["doc_id", "n_bytes", "n_tokens"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"))
    return rows.mapInArrow(count, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
