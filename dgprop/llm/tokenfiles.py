"""Token ids as flat binary files with 64-bit offsets, memory-mapped on reading.

A folder holds, for each part, ``<part>.ids`` (little-endian unsigned 16- or
32-bit ids, one document after the other, an end id after each), ``<part>.off``
(64-bit offsets of its documents in that file, one more than there are
documents), ``<part>.doc`` (64-bit document ids) and ``<part>.none`` (a byte for
each document, 1 if it has no id), and one table ``parts`` with each part's file name, documents, ids and the ids before it.  Parts are
ranges of doc_id, so that reading them in order gives ascending doc_id; the ids
before a part are the prefix sum over the parts, so that no task waits for another.

Files are written under names of the attempt's own and listed by the rows that
successful attempts return, so a lost executor or a second attempt leaves unused
files only.  On reading, files are mapped into memory where the store is a file
system of the machine, and read range by range elsewhere.  Null and empty texts
have just the end id; rows with equal doc_id stay, next to each other, in no fixed
order; rows without doc_id come first; a very long text is encoded whole, one at a
time.  Other columns are ignored.  An empty table gives no parts.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dgprop.llm.common import documents, new_folder, parts_for, shuffle_partitions, text_rows
from dgprop.llm.tokens import encoder

#: Bytes of text in a part, about; ranges are found by a sample, and rows of one doc_id stay together.
PART_BYTES = 256 << 20
_PART = "part int, file string, n_docs bigint, n_ids bigint"


def _open(folder: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (fs.LocalFileSystem(), folder)


class _Flat:
    """A flat file of numbers: mapped into memory where the store is local, else read range by range."""

    def __init__(self, store: fs.FileSystem, path: str, kind: str) -> None:
        self.kind, self.width = kind, np.dtype(kind).itemsize
        self.mapped, self.file = None, None
        if not isinstance(store, fs.LocalFileSystem):
            self.file = store.open_input_file(path)
        elif store.get_file_info(path).size:
            self.mapped = np.memmap(path, kind, "r")

    def part(self, first: int, end: int) -> np.ndarray:
        if self.file is not None:
            return np.frombuffer(self.file.read_at((end - first) * self.width, first * self.width), self.kind)
        return np.zeros(0, self.kind) if self.mapped is None else np.asarray(self.mapped[first:end])


def write_token_files(docs: DataFrame, folder: str, vocabulary: str, end_id: int, partitions: int | None = None, width: int | None = None) -> DataFrame:
    """Write the files; return the table of parts with ``base``, the ids before each part.

    ``width`` is the bytes of an id, 2 or 4; by default 2 if the vocabulary's ids fit.
    """
    spark = docs.sparkSession
    width = width or id_width(vocabulary, end_id)
    kind = {2: "<u2", 4: "<u4"}[width]
    end = end_id.to_bytes(4, "little")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        store, root = _open(folder)
        store.create_dir(root, recursive=True)
        part, name = TaskContext.get().partitionId(), f"{TaskContext.get().partitionId():08d}-{uuid.uuid4().hex}"
        n_docs = n_ids = 0
        with store.open_output_stream(f"{root}/{name}.ids") as ids, store.open_output_stream(f"{root}/{name}.off") as off, store.open_output_stream(f"{root}/{name}.doc") as doc, store.open_output_stream(f"{root}/{name}.none") as none:
            off.write(np.zeros(1, "<i8").tobytes())
            for batch in batches:
                for k in range(0, batch.num_rows, 512):
                    rows = batch.slice(k, 512)
                    coded = [e + end for e in encoder(vocabulary).encode(rows.column("text").to_pylist())]
                    lengths = np.array([len(e) // 4 for e in coded], np.int64)
                    flat = np.frombuffer(b"".join(coded), "<u4")
                    if width == 2 and len(flat) and int(flat.max()) > 0xFFFF:
                        raise ValueError("an id needs more than 16 bits")
                    ids.write(flat.astype(kind).tobytes())
                    off.write((n_ids + np.cumsum(lengths)).astype("<i8").tobytes())
                    doc.write(np.asarray(rows.column("doc_id").fill_null(0).to_numpy(zero_copy_only=False), "<i8").tobytes())
                    none.write(np.asarray(rows.column("doc_id").is_null().to_numpy(zero_copy_only=False), "u1").tobytes())
                    n_docs, n_ids = n_docs + len(coded), n_ids + int(lengths.sum())
        if n_docs:
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "file": [name], "n_docs": [n_docs], "n_ids": [n_ids]})

    rows = text_rows(docs)
    if not partitions:
        size = rows.agg(F.sum(F.octet_length("text"))).head()[0] or 0
        partitions = max(shuffle_partitions(spark), parts_for(size, PART_BYTES))
    placed = rows.repartitionByRange(partitions, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first())
    placed.mapInArrow(work, _PART).write.parquet(f"{folder}/written")
    # One row for each part: as many as the writer had tasks.
    parts = spark.read.schema(_PART).parquet(f"{folder}/written").orderBy("part").collect()
    bases = np.concatenate(([0], np.cumsum([p.n_ids for p in parts]))).astype(int).tolist()
    schema = T.StructType([*T._parse_datatype_string(_PART).fields, T.StructField("base", T.LongType())])
    table = spark.createDataFrame([(*p, b) for p, b in zip(parts, bases, strict=False)], schema)
    table.write.parquet(f"{folder}/parts")
    return spark.read.schema(schema).parquet(f"{folder}/parts")


def id_width(vocabulary: str, end_id: int) -> int:
    return 2 if max(encoder(vocabulary).tokenizer.get_vocab_size(with_added_tokens=True) - 1, end_id) <= 0xFFFF else 4


def read_token_files(spark: SparkSession, folder: str, width: int) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens and ids of every document."""
    kind = {2: "<u2", 4: "<u4"}[width]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = _open(folder)
        for batch in batches:
            for p in batch.to_pylist():
                ids, off, doc, none = (_Flat(store, f"{root}/{p['file']}.{x}", k) for x, k in (("ids", kind), ("off", "<i8"), ("doc", "<i8"), ("none", "u1")))
                for k in range(0, p["n_docs"], 256):
                    at = off.part(k, min(k + 256, p["n_docs"]) + 1)
                    yield pa.RecordBatch.from_arrays(
                        [
                            pa.array(doc.part(k, k + len(at) - 1), pa.int64(), mask=none.part(k, k + len(at) - 1) > 0),
                            pa.array(p["base"] + at[:-1], pa.int64()),
                            pa.array(np.diff(at), pa.int64()),
                            pa.array([ids.part(a, b).astype("<u4").tobytes() for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)], pa.binary()),
                        ],
                        ["doc_id", "start", "n_tokens", "ids"],
                    )

    parts = spark.read.parquet(f"{folder}/parts")
    n = max(1, parts.count())
    return parts.repartition(n, "part").mapInArrow(work, "doc_id bigint, start bigint, n_tokens bigint, ids binary")


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    folder = new_folder(spark, "token-files")
    vocabulary = public_tokenizers.path("byte_bpe_50k.json")
    write_token_files(documents(spark, sf_dir), folder, vocabulary, end_id=0)
    # Spark's crc32 is the unsigned one, of the little-endian 32-bit ids.
    return read_token_files(spark, folder, id_width(vocabulary, 0)).select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))
