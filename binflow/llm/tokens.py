"""BPE encoding, decoding and token counts of whole texts (operators 2 and 9)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binflow.llm.bpe import Counter, Encoder
from binflow.llm.common import once_per_worker, share_model, slices, tokenizer_path


def pack_ids(ids: np.ndarray) -> bytes:
    """Ids as little-endian unsigned 32-bit integers."""
    return ids.astype("<u4").tobytes()


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, decode: bool = False) -> DataFrame:
    """Encode every text: (id, tokens BINARY little-endian u32 [, decoded STRING]).

    Ids are those of the ``tokenizers`` library without added special tokens; special
    strings inside a text become their ids, as there. ``decode`` adds the text that the
    ids give back (malformed bytes become U+FFFD). Null and empty texts have no tokens.
    Rows keep their number and order: repeated and tied ids stay, a null id stays null,
    other columns, whatever their names, are not read; an empty table gives no rows. Long
    texts are cut into bounded pieces at safe borders.
    """
    path = path or tokenizer_path()
    shared, model_key = share_model(docs.sparkSession, path), path

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = once_per_worker(("encoder", model_key), lambda: Encoder(shared.value))
        for whole in batches:
            for batch in slices(whole, "text"):
                ids, n = coder.encode(batch.column(1).to_pylist())
                parts = np.split(ids, np.cumsum(n)[:-1])
                out = [batch.column(0), pa.array([pack_ids(p) for p in parts], pa.binary())]
                if decode:
                    out.append(pa.array([coder.decode(p).decode("utf-8", "replace") for p in parts], pa.string()))
                yield pa.RecordBatch.from_arrays(out, names)

    names = ["id", "tokens", *["decoded"] * decode]
    kind = dict(docs.dtypes)[id_col]
    picked = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    out = picked.mapInArrow(run, f"id {kind}, tokens binary" + ", decoded string" * decode)
    return out.withColumnRenamed("id", id_col)


def decode(rows: DataFrame, id_col: str = "doc_id", tokens_col: str = "tokens", path: str | None = None) -> DataFrame:
    """Text of packed ids: (id, decoded). Null or empty tokens give an empty text; an id outside the vocabulary is an error."""
    shared = share_model(rows.sparkSession, path or tokenizer_path())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = Encoder(shared.value, 1)
        for batch in batches:
            texts = [coder.decode(np.frombuffer(x or b"", "<u4").astype(np.int64)).decode("utf-8", "replace") for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["id", "decoded"])

    picked = rows.select(F.col(id_col).alias("id"), F.col(tokens_col).alias("tokens"))
    return picked.mapInArrow(run, f"id {dict(rows.dtypes)[id_col]}, decoded string").withColumnRenamed("id", id_col)


def count_tokens(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None) -> DataFrame:
    """Number of tokens of every text: (id, n_bytes, n_tokens).

    Pre-tokens that are proved, when the model is built, to encode alone as one token count
    one without merging; only the rest is merged, once per distinct word. Null and empty
    texts count zero. Rows keep their number and ties their order: repeated ids stay, a null id
    stays null; an empty table gives no rows; other columns, whatever their names, are not
    read. Long texts are cut into bounded pieces at safe borders; one row's text and its
    arrays are in a task's memory at once.
    """
    path = path or tokenizer_path()
    shared, model_key = share_model(docs.sparkSession, path), path

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = once_per_worker(("counter", model_key), lambda: Counter(shared.value))
        for whole in batches:
            for batch in slices(whole, "text"):
                n = counter.count(batch.column(1).to_pylist())
                size = pc.fill_null(pc.binary_length(batch.column(1)), 0).cast(pa.int64())
                yield pa.RecordBatch.from_arrays([batch.column(0), size, pa.array(n)], ["id", "n_bytes", "n_tokens"])

    picked = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    return picked.mapInArrow(run, f"id {dict(docs.dtypes)[id_col]}, n_bytes bigint, n_tokens bigint").withColumnRenamed("id", id_col)
