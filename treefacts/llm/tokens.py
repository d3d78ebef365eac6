"""Token ids of documents in files of wavelet matrices, in a stated order, and back.

Documents are dealt out by ranges of the order columns; each task encodes its texts and writes blocks of at most
block_tokens ids (or one document, if that is longer) as raw bytes through Spark's text sink, so the files go through the commit protocol of any
file system and a task that is run again leaves one file. Reading takes whole files; their size is bounded by how many
documents a task gets (rows_per_task).

Strings of the tokenizer's special tokens in a text get those tokens' ids, as the library gives them when nothing else is asked
for. Null or empty text: only the end id. Repeated rows: one entry each. A null document id is written as the lowest long.
"""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treefacts.llm import common, pieces, wavelet

END_ID = 2
BITS = 16
BLOCK_TOKENS = 1 << 21
FILE_BYTES = 8_000_000  #: of text that a file should hold, until there are MANY_FILES
MANY_FILES, MOST_BYTES = 4_096, 256_000_000  #: beyond so many files they grow up to MOST_BYTES each
CHUNK_CHARS = 1 << 17  #: characters of texts that are encoded together, whole texts
NULL_ID = -(1 << 63)
#: Texts of these characters are split by a plain pattern, all others by the tokenizer itself. Words are tried first: nothing else begins as they do.
#: PIECES says what a piece is; pieces.split() finds the same in many texts at once.
LETTERS = "A-Za-zÀ-ÖØ-öø-ÿ"
PLAIN = re.compile("[\t\n\r\x0b\x0c -~¡-©«-±´¶-¸»¿-ÿ–-„•…€]*")
PIECES = re.compile(f" ?[{LETTERS}]+| ?[0-9]+|'s|'t|'re|'ve|'m|'ll|'d| ?[^\\s{LETTERS}0-9]+|\\s+(?!\\S)|\\s+")


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_letters() -> np.ndarray:
    """The letter by which a byte-level vocabulary writes each byte: printable ones themselves, the others from U+0100 on."""
    printable = [b for b in range(256) if 0x21 <= b <= 0x7E or 0xA1 <= b <= 0xAC or 0xAE <= b]
    others = [b for b in range(256) if b not in printable]
    letters = {b: b for b in printable} | {b: 0x100 + i for i, b in enumerate(others)}
    return np.array([letters[b] for b in range(256)], "<u2")


class Pieces:
    """Ids (uint16) of texts, by pieces that the tokenizer encodes when they are first met.

    A byte-level tokenizer splits a text before it merges, and merges inside each piece only: the ids of a text are
    those of its pieces in turn. A bounded number of pieces is kept.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.tokenizer = Tokenizer.from_file(path)
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.merge, self.letters = self.tokenizer.model.tokenize, byte_letters()
        if self.tokenizer.get_vocab_size() > 1 << 16:
            raise ValueError("ids of over 16 bits")
        self.memory = pieces.Memory(self.of_pieces, END_ID)

    def of_pieces(self, some: list[bytes]) -> list[list[int]]:
        written = self.letters[np.frombuffer(b"".join(some), np.uint8)].tobytes().decode("utf-16-le")
        ends = accumulate(map(len, some))
        return [[t.id for t in self.merge(written[end - len(piece) : end])] for piece, end in zip(some, ends, strict=True)]

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, np.uint16).tobytes()

    def plain(self, text: str) -> bool:
        return PLAIN.fullmatch(text) is not None and not any(x in text for x in self.special)

    def encode_all(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of some texts, one after the other and each with its end id, and how many each has."""
        other = [i for i, text in enumerate(texts) if not self.plain(text)]
        left_out = set(other)
        mark = chr(pieces.MARK)
        ids, counts = self.memory.encode((mark.join("" if i in left_out else t for i, t in enumerate(texts)) + mark).encode())
        if other:
            found = [np.frombuffer(self.whole(texts[i]), np.uint16) for i in other]
            sizes = np.array([len(x) for x in found])
            ids = np.insert(ids, np.repeat((np.cumsum(counts) - counts)[other], sizes), np.concatenate(found))
            counts[other] += sizes
        return ids, counts

    def encode(self, text: str) -> bytes:
        return self.encode_all([text])[0][:-1].tobytes()


def files_for(n_bytes: int) -> int:
    small = -(-n_bytes // FILE_BYTES)
    return max(1, small if small <= MANY_FILES else max(MANY_FILES, -(-n_bytes // MOST_BYTES)))


_encoders: dict[str, Pieces] = {}


def encoder(path: str) -> Pieces:
    if path not in _encoders:
        _encoders[path] = Pieces(path)
    return _encoders[path]


def some_texts(column: pa.Array) -> Iterator[tuple[int, list[str]]]:
    """The texts (null as empty) of a column, some characters at a time, and the row of the first."""
    first, texts, size = 0, [], 0
    for text in column:
        texts.append(text.as_py() or "")
        size += len(texts[-1])
        if size >= CHUNK_CHARS:
            yield first, texts
            first, texts, size = first + len(texts), [], 0
    if texts:
        yield first, texts


def write(docs: DataFrame, folder: str, order: list[Column], id_col: str = "doc_id", text_col: str = "text", path: str | None = None, n_files: int | None = None) -> None:
    """Writes the token files of docs, documents in the given order over the files by name and inside each."""
    path = path or tokenizer_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(path).encode_all
        ids, counts, parts, total = [], [], [], 0

        def block() -> pa.RecordBatch:
            raw = wavelet.to_bytes(np.array(ids, np.int64), np.array(counts, np.int64), np.concatenate(parts), BITS)
            return pa.RecordBatch.from_arrays([pa.array([raw[:-1]], pa.binary())], names=["value"])  # the sink adds the line feed

        for batch in batches:
            for first, texts in some_texts(batch.column(1)):
                flat, sizes = encode(texts)
                ends = np.cumsum(sizes).tolist()
                for doc, end, size in zip(batch.column(0).slice(first, len(texts)).to_pylist(), ends, sizes.tolist(), strict=True):
                    if ids and total + size > BLOCK_TOKENS:
                        yield block()
                        ids, counts, parts, total = [], [], [], 0
                    ids.append(NULL_ID if doc is None else doc)
                    counts.append(size)
                    parts.append(flat[end - size : end])
                    total += size
        if ids:
            yield block()

    chosen = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"), *[c.alias(f"order{i}") for i, c in enumerate(order)])
    keys = [f"order{i}" for i in range(len(order))]
    if n_files is None:
        n = docs.agg(F.sum(F.octet_length(F.col(text_col)))).first()[0] or 0
        n_files = files_for(n)
    dealt = chosen.repartitionByRange(n_files, *keys).sortWithinPartitions(*keys).select("id", "text")
    dealt.mapInArrow(run, "value binary").select(F.col("value").cast("string").alias("value")).write.option("compression", "none").text(folder)


def read(spark: SparkSession, folder: str, id_name: str = "doc_id") -> DataFrame:
    """One row per document of the files: id, start (ids of all documents before it), n_tokens, ids_crc32 (of the ids as
    32-bit integers), and file, block and place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                before = 0
                for number, shard in enumerate(wavelet.from_bytes(content.as_py())):
                    flat = shard.matrix.decode(np.uint32)
                    ends = np.cumsum(shard.counts.astype(np.int64))
                    crcs = [zlib.crc32(flat[e - c : e]) for e, c in zip(ends.tolist(), shard.counts.tolist(), strict=True)]
                    n = len(ends)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([None if i == NULL_ID else i for i in shard.doc_ids.tolist()], pa.int64()), pa.array(before + ends - shard.counts), pa.array(shard.counts.astype(np.int64)), pa.array(crcs, pa.int64()), pa.array([name] * n), pa.array([number] * n, pa.int32())],
                        names=[id_name, "start", "n_tokens", "ids_crc32", "file", "block"],
                    )
                    before += int(ends[-1]) if n else 0

    files = spark.read.format("binaryFile").load(folder).select(F.element_at(F.split("path", "/"), -1).alias("file"), "content")
    docs = files.mapInArrow(run, f"`{id_name}` long, start long, n_tokens long, ids_crc32 long, file string, block int")
    docs = common.materialise(docs, "token-docs")
    sizes = docs.groupBy("file").agg(F.sum("n_tokens").alias("size"))
    # one row per file stands in this window, however many documents there are
    before = sizes.select("file", F.coalesce(F.sum("size").over(Window.orderBy("file").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    return docs.join(before, "file").withColumn("start", F.col("start") + F.col("before")).select(id_name, "start", "n_tokens", "ids_crc32", "file", "block")


def round_trip(docs: DataFrame, order: list[Column], id_col: str = "doc_id", text_col: str = "text", path: str | None = None, n_files: int | None = None) -> DataFrame:
    """Writes the token files in the shared folder and reads them back."""
    folder = common.new_folder(docs.sparkSession, "token-files")
    write(docs, folder, order, id_col, text_col, path, n_files)
    return read(docs.sparkSession, folder, id_col)
