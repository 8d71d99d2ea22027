"""Byte-level BPE: encoding with offsets, and decoding, over Arrow batches.

The ``tokenizers`` library merges the pre-tokens; a rank file is turned into
its vocabulary and merges, every pair of known tokens whose concatenation is
known being a merge at that token's rank.  Token bytes become characters
through the byte-to-character table; decoding reverses that table.

Defined results: a null text encodes like the empty one, to no ids; a null id
column decodes to empty bytes; ids outside of the vocabulary raise.  Rows repeat
if the input's do; other columns of the input are not read.
"""

from __future__ import annotations

import base64
import json
from collections.abc import Iterator
from functools import cache, lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from ..session import ship_package
from .pretokens import IdMemo
from .textbatch import binary_array, binary_flat, ranges, text_chunks


@cache
def byte_characters() -> dict[int, str]:
    """The printable stand-in of each byte: itself where it prints, else from U+0100 on."""
    shown = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    hidden = [b for b in range(256) if b not in shown]
    return {b: chr(b) for b in sorted(shown)} | {b: chr(0x100 + k) for k, b in enumerate(hidden)}


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def tokenizer_json(path: str) -> str:
    """The tokenizer that a rank file describes, in the tokenizers library's format."""
    ranks = read_ranks(path)
    name = byte_characters()
    shown = {t: "".join(name[b] for b in t) for t in ranks}
    merges = [[shown[t[:k]], shown[t[k:]]] for t in sorted(ranks, key=ranks.get) for k in range(1, len(t)) if t[:k] in ranks and t[k:] in ranks]
    model = {"type": "BPE", "dropout": None, "unk_token": None, "continuing_subword_prefix": None, "end_of_word_suffix": None, "fuse_unk": False, "byte_fallback": False, "ignore_merges": True, "vocab": {shown[t]: r for t, r in ranks.items()}, "merges": merges}
    level = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": False, "use_regex": False}
    return json.dumps({"version": "1.0", "truncation": None, "padding": None, "added_tokens": [], "normalizer": None, "pre_tokenizer": level, "post_processor": None, "decoder": level, "model": model})


@lru_cache(maxsize=4)
def library(path: str) -> Tokenizer:
    t = Tokenizer.from_file(path) if path.endswith(".json") else Tokenizer.from_str(tokenizer_json(path))
    t.encode_special_tokens = True
    return t


_memos: dict[str, IdMemo] = {}


def memo(path: str, spec: str | None = None) -> IdMemo:
    """A process's memo for a tokenizer; ``spec`` is its description, where it isn't to be made from the file here."""
    if path not in _memos:
        _memos[path] = _new_memo(Tokenizer.from_str(spec) if spec else library(path))
    return _memos[path]


def _new_memo(t: Tokenizer) -> IdMemo:
    t.encode_special_tokens = True
    return IdMemo(lambda pieces: [e.ids for e in t.encode_batch_fast(pieces, add_special_tokens=False)])


@lru_cache(maxsize=4)
def token_bytes(path: str) -> tuple[np.ndarray, np.ndarray]:
    """All tokens' bytes one after another, and each id's offset there."""
    if path.endswith(".json"):
        back = {c: b for b, c in byte_characters().items()}
        with open(path) as f:
            model = json.load(f)
        vocab = {bytes(back[c] for c in shown): i for shown, i in model["model"]["vocab"].items() if all(c in back for c in shown)}
    else:
        vocab = read_ranks(path)
    parts = [b""] * (max(vocab.values()) + 1)
    for token, i in vocab.items():
        parts[i] = token
    return np.frombuffer(b"".join(parts), np.uint8), np.concatenate([[0], np.cumsum([len(p) for p in parts], dtype=np.int64)])


def _spans(chunk, ids: np.ndarray, off: np.ndarray, path: str) -> np.ndarray:
    """(first, past) characters of each token in its text; a token that holds part of a character spans it whole."""
    _, tok = token_bytes(path)
    size = np.diff(tok)[ids]
    past = np.cumsum(size)
    lead = (np.frombuffer(chunk.raw, np.uint8) & 0xC0) != 0x80
    char = np.cumsum(lead, dtype=np.int64)  # characters begun up to and with each byte
    first = char[past - size] - 1
    last = char[past - 1]
    base = np.repeat(chunk.char_off[:-1], np.diff(off))
    return np.stack([first - base, last - base], axis=1).astype(np.uint32)


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", with_offsets: bool = False, with_decoded: bool = False) -> DataFrame:
    """(id, n_tokens, ids[, offsets][, decoded]): ids as little-endian unsigned 32-bit integers; offsets as pairs of those.

    ``with_decoded`` decodes the ids in the same pass: one Python worker for a task instead of two.
    """
    spark = docs.sparkSession
    ship_package(spark)
    spec = spark.sparkContext.broadcast(None if path.endswith(".json") else tokenizer_json(path))  # as large as the vocabulary

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, chunk in text_chunks(batch.column(1)):
                ids, off = memo(path, spec.value).tokens(chunk)
                columns = [batch.column(0).slice(row, chunk.n), pa.array(np.diff(off)), binary_array(ids.astype("<u4").tobytes(), off * 4)]
                if with_offsets:
                    columns.append(binary_array(_spans(chunk, ids, off, path).astype("<u4").tobytes(), off * 8))
                if with_decoded:
                    columns.append(decoded_bytes(ids, off, path))
                yield pa.RecordBatch.from_arrays(columns, names)

    kind = docs.schema[id_col].dataType.simpleString()
    names = [id_col, "n_tokens", "ids", *["offsets"] * with_offsets, *["decoded"] * with_decoded]
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_tokens long, ids binary" + ", offsets binary" * with_offsets + ", decoded binary" * with_decoded)


def decoded_bytes(ids: np.ndarray, off: np.ndarray, path: str) -> pa.Array:
    """Bytes of each id list ids[off[k] : off[k + 1]]."""
    table, tok = token_bytes(path)
    n = np.diff(tok)[ids]
    ends = np.concatenate([[0], np.cumsum(n)])
    return binary_array(table[ranges(tok[ids], n)].tobytes(), ends[off])


def decode(encoded: DataFrame, path: str, keep: tuple[str, ...] = ("doc_id",), ids_col: str = "ids") -> DataFrame:
    """The kept columns and ``decoded``, the ids' bytes.  Tokens may split characters, so bytes come first; see ``as_text``."""
    ship_package(encoded.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column, row = batch.column(batch.num_columns - 1), 0
            while row < batch.num_rows:  # bounded parts of the batch
                flat, off = binary_flat(column.slice(row, 512))
                out = decoded_bytes(flat.view("<u4"), off // 4, path)
                yield pa.RecordBatch.from_arrays([*(c.slice(row, 512) for c in batch.columns[:-1]), out], [*keep, "decoded"])
                row += 512

    kinds = ", ".join(f"`{c}` {encoded.schema[c].dataType.simpleString()}" for c in keep)
    return encoded.select(*keep, ids_col).mapInArrow(run, f"{kinds}, decoded binary")


def as_text(decoded: Column) -> Column:
    """Decoded bytes as text; what isn't whole characters (a cut id list) becomes U+FFFD."""
    return F.make_valid_utf8(decoded.cast("string"))


def stream_text(ids: Iterator[int], path: str) -> Iterator[str]:
    """Text of ids as they come, each character as soon as its last byte is there."""
    import codecs

    table, tok = token_bytes(path)
    reader = codecs.getincrementaldecoder("utf-8")("replace")
    for i in ids:
        if part := reader.decode(table[tok[i] : tok[i + 1]].tobytes()):
            yield part
    if rest := reader.decode(b"", True):
        yield rest
