"""Token ids in wavelet-matrix shards, in ascending document order.

Documents are range-partitioned and sorted by id; each partition is encoded and cut into shards of about
``shard_tokens`` at document ends, and each shard becomes one file in ``folder``. A file is written under
an attempt's own name and then renamed, and its final name depends only on its place, so a repeated task
replaces it by the same bytes. The manifest (one row a shard) has each file's first position; readers
get ids back from the files alone.

Null and empty texts give the end id only. Rows with equal ids stand side by side, by text. Rows
without id come first and keep a null id. Very long texts become a shard of their own. An empty table
writes no files.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.llm.tokens import encoder, tokenizer_path
from ivfspark.llm.wavelet import WaveletMatrix
from ivfspark.operators.prefix import running_total
from ivfspark.plans.scratch import materialize, scratch_path

END_ID = 1
SHARD_TOKENS = 1 << 22
PARTITION_BYTES = 16 << 20
#: Stands for a null id in a shard's id list; real ids may not use it.
_NO_ID = np.iinfo(np.int64).min


def put_file(folder: str, name: str, data: bytes) -> str:
    """Write ``data`` whole or not at all, on any file system that Arrow knows by URI."""
    from pyarrow import fs

    system, root = fs.FileSystem.from_uri(folder if "://" in folder or folder.startswith("/") else f"file:{folder}")
    system.create_dir(root, recursive=True)
    draft = f"{root}/.{name}.{uuid.uuid4().hex}"
    with system.open_output_stream(draft) as out:
        out.write(data)
    system.move(draft, f"{root}/{name}")
    return f"{folder}/{name}"


def get_file(path: str) -> bytes:
    from pyarrow import fs

    system, place = fs.FileSystem.from_uri(path.replace("file:///", "/").replace("file:/", "/"))
    with system.open_input_stream(place) as source:
        return source.read()


def write_shards(
    docs: DataFrame,
    folder: str,
    path: str | None = None,
    end_id: int = END_ID,
    shard_tokens: int = SHARD_TOKENS,
    split_spaces: bool = True,
) -> DataFrame:
    """Encode ``docs(doc_id, text)`` into shard files; returns the manifest
    ``(part, piece, path, n_docs, n_tokens, n_bytes, start)``."""
    path = path or tokenizer_path()
    folder = folder.replace("file:///", "/").replace("file:/", "/")
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    size = source.agg(F.sum(F.octet_length("text") + 16)).first()[0] or 0
    n_parts = max(1, -(-size // PARTITION_BYTES))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, piece = TaskContext.get().partitionId(), 0
        coder, end = encoder(path, split_spaces), np.array([end_id], "<u4").tobytes()
        ids, rows, held = [], [], 0

        def shard() -> pa.RecordBatch:
            tokens = np.frombuffer(b"".join(ids), "<u4")
            lengths = np.array([len(x) // 4 for x in ids], np.uint64)
            matrix = WaveletMatrix.build(tokens, np.array(rows, np.int64), lengths)
            data = matrix.to_bytes()
            name = f"shard-{part:08d}-{piece:06d}.wvm"
            done = put_file(folder, name, data)
            values = [[part], [piece], [done], [len(rows)], [len(tokens)], [len(data)]]
            return pa.RecordBatch.from_arrays([pa.array(v) for v in values], ["part", "piece", "path", "n_docs", "n_tokens", "n_bytes"])

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids.append(coder.encode(text.as_py()) + end)
                rows.append(_NO_ID if doc is None else doc)
                held += len(ids[-1]) // 4
                if held >= shard_tokens:
                    yield shard()
                    ids, rows, held, piece = [], [], 0, piece + 1
        if rows:
            yield shard()

    dealt = source.repartitionByRange(n_parts, "doc_id") if n_parts > 1 else source.coalesce(1)
    schema = "part long, piece long, path string, n_docs long, n_tokens long, n_bytes long"
    written = materialize(dealt.sortWithinPartitions("doc_id", "text").mapInArrow(kernel, schema), "manifest")
    return running_total(written, F.floor(F.col("part") / 1024), [F.col("part"), F.col("piece")], F.col("n_tokens"), "start")


def read_shards(manifest: DataFrame) -> DataFrame:
    """Per document, from the files: ``doc_id, start, n_tokens, ids_crc32``."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                matrix = WaveletMatrix.from_bytes(get_file(path))
                raw = memoryview(matrix.ids().astype("<u4").tobytes())
                ends = np.cumsum(matrix.lengths.astype(np.int64))
                starts = ends - matrix.lengths.astype(np.int64)
                crc = [zlib.crc32(raw[4 * s : 4 * e]) for s, e in zip(starts.tolist(), ends.tolist(), strict=True)]
                doc = pa.array(matrix.doc_ids, mask=matrix.doc_ids == _NO_ID)
                yield pa.RecordBatch.from_arrays(
                    [doc, pa.array(starts + start), pa.array(matrix.lengths.astype(np.int64)), pa.array(crc, pa.int64())],
                    ["doc_id", "start", "n_tokens", "ids_crc32"],
                )

    files = manifest.select("path", "start").repartition(max(1, manifest.count()), "path")
    return files.mapInArrow(kernel, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_output(docs: DataFrame, folder: str | None = None, **options) -> DataFrame:
    """Write ``docs`` as shards and read every document's place and check sum back from the files."""
    return read_shards(write_shards(docs, folder or scratch_path(docs.sparkSession, "tokens"), **options))


def open_shard(path: str) -> WaveletMatrix:
    """One shard file, for access, counting and occurrence look-up."""
    return WaveletMatrix.from_bytes(get_file(path))


