"""Packing by power-of-two decomposition.

A document of ``n`` ids is cut into as many full sequences (2048) as fit and the
binary digits of the rest, longest first, so every piece has a power-of-two
length, fills a sequence of its own without padding, and no sequence holds two
documents.  Pieces of equal length share a bucket, from which batches of one
shape are drawn.

Ids come from a public tokenizer file whose path is a parameter.  Where the file
lower-cases and cuts a text into runs of letters, digits and marks (the steps in
``KNOWN_STEPS``; the file is compared with them), the same cut is made here for texts
of Latin characters, and a bounded table from run to ids stands before the file's
merge model.  Any other text, and every text under any other file, takes the plain call.

Defined results: null or empty text is the end id alone (one piece of length
1); repeated rows are packed row by row; a null ``doc_id`` is carried; extra
columns pass unread; an empty table gives an empty result.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import ship, slices, spread

MAX_LENGTH = 2048
END_ID = 1
RUNS_KEPT = 600_000

# The file's letters, digits and white space below U+0250, and its cut.
_LETTER = "a-z\u00aa\u00b5\u00ba\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f"
_DIGIT = "0-9\u00b2\u00b3\u00b9\u00bc-\u00be"
_SPACE = " \t-\r\u0085\u00a0"
_CUT = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTER}]+|[{_DIGIT}]|[^{_SPACE}{_LETTER}{_DIGIT}]+")

#: Outside the Latin range, or a special token's mark, or a capital whose lower case leaves the range.
_OTHER = re.compile("[\u0250-\U0010ffff\u0130]|<\\|")

# What a file must say for the cut above to be its own.
KNOWN_STEPS = {
    "normalizer": {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]},
    "pre_tokenizer": {
        "type": "Sequence",
        "pretokenizers": [
            {"type": "Split", "pattern": {"Regex": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"}, "behavior": "Removed", "invert": True},
            {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
        ],
    },
    "truncation": None,
    "padding": None,
}


def cut_is_known(path: str) -> bool:
    """Whether the file's own steps are those that :class:`RunTable` takes without it."""
    with open(path, encoding="utf-8") as f:
        told = json.load(f)
    same = all(told.get(k) == v for k, v in KNOWN_STEPS.items())
    # added tokens are found before the cut; texts with their mark take the plain call
    return same and not told["model"].get("dropout") and all(t["content"].startswith("<|") for t in told.get("added_tokens", []))


_tables: dict[str, "RunTable"] = {}


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def byte_letters() -> dict[int, str]:
    """The printable stand-in of each byte: printable Latin-1 stands for itself, the rest follow from U+0100."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class RunTable(dict):
    """Run to its ids as little-endian 32-bit bytes; emptied when it outgrows its bound."""

    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.letters = byte_letters()
        self.known = cut_is_known(path)

    def __missing__(self, run: str) -> bytes:
        seen = run if run.isascii() else run.encode().decode("latin-1")
        ids = b"".join([t.id.to_bytes(4, "little") for t in self.model.tokenize(seen.translate(self.letters))])
        self[run] = ids
        return ids

    def ids(self, text: str) -> bytes:
        if not self.known or _OTHER.search(text):
            return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()
        if len(self) > RUNS_KEPT:
            self.clear()
        return b"".join(map(self.__getitem__, _CUT.findall(text.lower())))


def pieces(n: int, largest: int = MAX_LENGTH) -> list[tuple[int, int]]:
    """(start, length) of the power-of-two pieces of n ids, longest first."""
    out, start = [], 0
    while n - start >= largest:
        out.append((start, largest))
        start += largest
    size = largest >> 1
    while size:
        if (n - start) & size:
            out.append((start, size))
            start += size
        size >>= 1
    return out


SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, ids binary"


def _pack(path: str, largest: int, with_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if path not in _tables:
            _tables[path] = RunTable(path)
        table = _tables[path]
        end = np.array([END_ID], dtype="<u4").tobytes()
        for batch in slices(batches, "text", 1 << 20):
            docs = batch.column(0).to_pylist()
            rows: list[list] = [[], [], [], [], [], []]
            for doc, ids in zip(docs, (table.ids(t or "") for t in batch.column(1).to_pylist())):
                ids += end
                n = len(ids) // 4
                for start, length in pieces(n, largest):
                    part = ids[4 * start : 4 * (start + length)]
                    for column, value in zip(rows, (doc, start, length, zlib.crc32(part), n, part if with_ids else None)):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, type=pa.binary() if i == 5 else pa.int64()) for i, c in enumerate(rows)], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "ids"])

    return run


def pack(spark: SparkSession, docs: DataFrame, tokenizer: str | None = None, largest: int = MAX_LENGTH, with_ids: bool = True) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, ids, bucket, sequence_id, offset.

    ``bucket`` is the power of two of the length; each piece is a sequence.
    """
    ship(spark)
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))
    out = spread(rows).mapInArrow(_pack(tokenizer or default_tokenizer(), largest, with_ids), SCHEMA)
    return out.select("*", F.log2("length").cast("int").alias("bucket"), F.monotonically_increasing_id().alias("sequence_id"), F.lit(0).cast("long").alias("offset"))


def write_buckets(packed: DataFrame, path: str, salts: int = 16) -> None:
    """Pieces below one folder per length, for batches of one shape; a length's pieces are dealt over ``salts`` tasks."""
    dealt = packed.repartition("bucket", F.pmod(F.xxhash64("doc_id", "start"), F.lit(salts)))
    dealt.write.mode("overwrite").partitionBy("bucket").parquet(path)


def digest(spark: SparkSession, docs: DataFrame) -> DataFrame:
    return pack(spark, docs, with_ids=False).drop("ids")
