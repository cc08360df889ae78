"""Token counts: Arrow batches in, lengths only out; batches balanced by bytes, long texts cut at safe boundaries."""

from __future__ import annotations

import json
from array import array
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlens.llm.textkernel import chunks_of_bytes
from pairlens.llm.units import UnitMemo

#: Text bytes handled at once.
WORK_BYTES = 1 << 20
_memos: dict[str, UnitMemo] = {}


def piece_encoder(path: str) -> Callable[[list[str], bool], list]:
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    inner = [i for i in range(model.get_piece_size()) if "▁" in model.id_to_piece(i).lstrip("▁")]
    if inner:
        raise ValueError("this model has pieces with an inner word mark; its texts can't be cut at spaces")
    # a unit's own space is dropped and comes back as the mark that the model puts before any text
    return lambda units, leading: [array("I", x).tobytes() for x in model.encode(units, num_threads=1)]


def byte_encoder(path: str) -> Callable[[list[str], bool], list]:
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(path)
    model.no_truncation()
    model.no_padding()
    added = [x["content"] for x in json.loads(model.to_str())["added_tokens"]]
    line = model.encode("\n", add_special_tokens=False).ids
    if len(line) != 1:
        raise ValueError("a line feed must be one token of its own")

    def encode(units: list[str], leading: bool) -> list[bytes]:
        # units without white space of any kind: line feeds part such units, as they stay tokens of their own
        plain = [i for i, u in enumerate(units) if u.split() == [u]]
        units = units if leading else [" " + u for u in units]
        if added:
            plain = [i for i in plain if not any(a in units[i] for a in added)]
        out: list = [None] * len(units)
        if plain:
            ids = np.array(model.encode("\n".join([units[i] for i in plain]), add_special_tokens=False).ids, "<u4")
            stops = (np.flatnonzero(ids == line[0]) * 4).tolist()
            raw = ids.tobytes()
            for i, a, b in zip(plain, [-4, *stops], [*stops, len(raw)], strict=True):
                out[i] = raw[a + 4 : b]
        rest = [i for i, x in enumerate(out) if x is None]
        for i, x in zip(rest, model.encode_batch([units[i] for i in rest], add_special_tokens=False), strict=True):
            out[i] = array("I", x.ids).tobytes()
        return out

    return encode


def memo(path: str) -> UnitMemo:
    """The worker's memo for a tokenizer file: sentencepiece for .model, tokenizers for .json."""
    if path not in _memos:
        _memos[path] = UnitMemo(piece_encoder(path) if path.endswith(".model") else byte_encoder(path))
    return _memos[path]


def count_tokens(docs: DataFrame, tokenizer: str, text: str = "text", key: str = "doc_id", limit: int = 4096) -> DataFrame:
    """key, n_bytes, n_tokens, over_limit for each row; a null or empty text has 0 of either. tokenizer: a file's path.

    Repeated rows give repeated results, other columns are ignored. Nothing is cut off: a long text is cut into units
    whose lengths add up.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = memo(tokenizer)
        for batch in batches:
            texts, n = batch.column(1), []
            for part in chunks_of_bytes(texts, WORK_BYTES):
                n.append(np.diff(count(part)[1]))
            sizes = pc.coalesce(pc.binary_length(texts), pa.scalar(0, pa.int32())).cast(pa.int64())
            tokens = pa.array(np.concatenate(n) if n else np.zeros(0, np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), sizes, tokens], names=["key", "n_bytes", "n_tokens"])

    kind = docs.schema[key].dataType.simpleString()
    plain = docs.select(F.col(key).alias("key"), F.col(text).cast("binary").alias("text"))
    out = plain.mapInArrow(run, f"key {kind}, n_bytes bigint, n_tokens bigint")
    return out.select(F.col("key").alias(key), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
