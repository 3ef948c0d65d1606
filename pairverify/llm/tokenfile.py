"""Flat files of token ids with 64-bit document offsets.

A file holds the ids of its documents one after the other as unsigned little-endian integers of 2 or 4 bytes, each
document closed by the end id, and then a footer: for each document its id, whether that id is there, and where it
starts, then the file's number, its number of documents, the bytes an id takes and a mark. The last thing in a file is
one more end id, which belongs to no document. Files are ordered by number; a document's start in the whole corpus is
its start in the file plus the ids in all files before, a prefix sum over one number per file.

There are as many files as the corpus's bytes need, so a file never outgrows a task. Spark's own text sink writes them
(the end id is its line end), so they reach any store that Spark can write, with its commit protocol; a lost task writes
its file again. Readers map files below file:/ into memory, where ids stay on disk until they are touched, and take the
bytes from Spark's binary reader for other stores.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._common import materialize, scratch_dir, ship, text_or_empty
from .tokenizing import ChunkEncoder, encoder, tokenizer_file

MARK = 0x544F4B46494C4531
#: Chunks that a worker's encoder keeps; with files of 16 MB this is what a task holds at a time.
MOST_KEPT = 400_000


def footer(keys: list[np.ndarray], there: list[np.ndarray], counts: list[np.ndarray], part: int, width: int) -> bytes:
    """Ids of a file's documents, whether they are there, and their starts, from arrays by batch."""
    keys, there, counts = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (keys, there, counts))
    starts = np.concatenate([[0], np.cumsum(counts)])
    return keys.astype("<i8").tobytes() + there.astype(np.uint8).tobytes() + starts.astype("<i8").tobytes() + np.array([part, len(keys), width, MARK], "<i8").tobytes()


def parse(data) -> tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """File number, all ids, document ids, whether those are there, and starts (one more at the end), from a file's bytes or memory map."""
    data = data if isinstance(data, np.ndarray) else np.frombuffer(data, np.uint8)
    for width in (2, 4):
        tail = data[len(data) - width - 32 : len(data) - width].tobytes()
        part, n, own, mark = np.frombuffer(tail, "<i8") if len(tail) == 32 else (0, 0, 0, 0)
        if mark == MARK and own == width:
            break
    else:
        raise ValueError("not a token file, or one that is cut off")
    at = len(data) - width - 32 - (8 * n + n + 8 * (n + 1))
    body = data[at : len(data) - width - 32].tobytes()
    keys, there, starts = np.frombuffer(body, "<i8", n), np.frombuffer(body, np.uint8, n, 8 * n) > 0, np.frombuffer(body, "<i8", n + 1, 9 * n)
    return int(part), data[: int(starts[-1]) * width].view(f"<u{width}"), keys, there, starts


def open_file(path: str):
    """Map a local file into memory and parse it; ids stay on disk until they are touched."""
    return parse(np.memmap(path, np.uint8, "r"))


def write(docs: DataFrame, path: str, tokenizer: str | None = None, style: str = "words", end_id: int = 2, id_col: str = "doc_id", text_col: str = "text", file_bytes: int = 16 << 20) -> None:
    """Write all documents in ascending id order (nulls first; rows that repeat an id by a hash of their texts).

    A null or empty text gives the end id alone. Files take about `file_bytes` of text each, rows that share an id also
    spread over several. The end id's bytes must be valid UTF-8. Ids have to be whole numbers. Other columns of docs play
    no part, whatever their names. An empty table gives files without documents or none.
    """
    ship()
    file = tokenizer or tokenizer_file("word_bpe_49k.json")
    vocabulary = ChunkEncoder(file, style).vocabulary
    width = 2 if max(vocabulary, end_id + 1) <= 1 << 16 else 4
    end = int(end_id).to_bytes(width, "little").decode()
    rows = docs.select(F.col(id_col).cast("long").alias("id"), text_or_empty(text_col).alias("text"))
    total, longest = rows.agg(F.sum(F.octet_length("text") + 16), F.max(F.octet_length("text"))).first()
    files = (total or 0) // max(file_bytes, longest or 0) + 1
    order = ["id", F.xxhash64("text"), F.monotonically_increasing_id()]
    rows = rows.repartitionByRange(files, *order).sortWithinPartitions("id", F.xxhash64("text"))

    def encode(batches):
        from pyspark import TaskContext

        coder, keys, there, counts = encoder(file, style, MOST_KEPT), [], [], []
        for b in batches:
            column = b.column(0)
            keys.append(column.fill_null(0).to_numpy(zero_copy_only=False))
            there.append(column.is_valid().to_numpy(zero_copy_only=False))
            for i, j, ids, off in coder.encode(b.column(1)):
                raw = ids.astype(f"<u{width}").tobytes()
                o = (off * width).tolist()
                counts.append(np.diff(off) + 1)
                yield pa.RecordBatch.from_arrays([pa.array([raw[o[r] : o[r + 1]] for r in range(j - i)], pa.binary())], ["row"])
        if keys:
            yield pa.RecordBatch.from_arrays([pa.array([footer(keys, there, counts, TaskContext.get().partitionId(), width)], pa.binary())], ["row"])

    rows.mapInArrow(encode, "row binary").select(F.col("row").cast("string").alias("value")).write.option("lineSep", end).text(path)


def read(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """One row per document of the files below path: doc_id, start, n_tokens, ids_crc32 (and the ids, if asked)."""
    ship()
    names = ["doc_id", "own", "n_tokens", "ids_crc32", "part"] + ["ids"] * with_ids
    schema = "doc_id long, own long, n_tokens long, ids_crc32 long, part int" + ", ids array<int>" * with_ids

    def documents(parsed):
        part, ids, keys, there, starts = parsed
        for lo in range(0, len(keys), 4096):
            own = [ids[starts[k] : starts[k + 1]].astype("<u4") for k in range(lo, min(lo + 4096, len(keys)))]
            cols = [pa.array(keys[lo : lo + 4096], pa.int64(), mask=~there[lo : lo + 4096]), pa.array(starts[lo : lo + len(own)]), pa.array([len(x) for x in own], pa.int64())]
            cols += [pa.array([zlib.crc32(x.tobytes()) for x in own], pa.int64()), pa.array(np.full(len(own), part, np.int32))]
            cols += [pa.array([x.astype(np.int32) for x in own], pa.list_(pa.int32()))] * with_ids
            yield pa.RecordBatch.from_arrays(cols, names)

    def mapped(batches):
        from urllib.parse import unquote, urlsplit

        for b in batches:
            for where in b.column(0).to_pylist():
                yield from documents(open_file(unquote(urlsplit(where).path)))

    def fetched(batches):
        for b in batches:
            for content in b.column(0):
                yield from documents(parse(content.as_buffer()))

    files = spark.read.format("binaryFile").load(path)
    paths = [r["path"] for r in files.select("path").where("length > 0").collect()]  # one for each file
    if all(p.startswith("file:/") for p in paths):
        rows = spark.createDataFrame([(p,) for p in paths], "path string").repartition(max(1, len(paths))).mapInArrow(mapped, schema)
    else:
        rows = files.select("content").mapInArrow(fetched, schema)
    found = materialize(rows, "read")
    sums = found.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    bases = sums.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))  # one row per file
    return found.join(F.broadcast(bases), "part").select("doc_id", (F.col("own") + F.col("base")).alias("start"), "n_tokens", "ids_crc32", *["ids"] * with_ids)


def round_trip(docs: DataFrame, **options) -> DataFrame:
    """Write docs to fresh files in the shared scratch folder and read the files back. An empty table gives no rows."""
    spark = docs.sparkSession
    path = f"{scratch_dir(spark)}/tokens"
    from ._common import freed_shuffles

    with freed_shuffles(spark):
        write(docs, path, **options)
    return read(spark, path)
