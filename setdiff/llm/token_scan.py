"""Token counts of flat token files without an index.

A file is a run of little-endian 16-bit ids; every document ends with the end-of-document id. Nothing else
says where documents are. Files are cut into blocks of equal bytes; each block is read by a
range read and searched for the identifier with one vectorised comparison. A block reports the gaps between
its separators and two open ends. A prefix scan over the block summaries (separators so
far; tokens open at the block's start) then gives every document its number and its whole length, so documents that
cross one or many blocks come out right and no block waits for another. The scan works in two levels, so that no task
has the blocks of a long file to itself.

Tokens after the last separator of a file are reported as an unterminated document. Empty files give
no rows, a document without tokens counts zero.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import bpe
from .common import keep, lean, scratch, small

BLOCK = 4 << 20
#: Blocks that the first level of the prefix scan takes together.
SPAN = 512
WIDTH = 2


def scan_blocks(spark: SparkSession, path: str, eod: int, block: int = BLOCK) -> DataFrame:
    """One row per block of each file under ``path``: file, block, n_tokens, n_eod, head, tail, inner.

    ``head`` counts the tokens before the first separator, ``tail`` those after the last (all tokens, both, if there is none); ``inner``
    has the lengths of the documents that begin and end in the block.
    """
    if block % WIDTH:
        raise ValueError("a block holds whole tokens")
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select(F.col("path").alias("file"), "length")
    last = F.ceil(F.col("length") / block) - 1
    cuts = files.where("length > 1").select("file", "length", F.explode(F.sequence(F.lit(0).cast("long"), last)).alias("block"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, length, k in zip(*(c.to_pylist() for c in b.columns), strict=True):
                store, name = fs.FileSystem.from_uri(file)
                with store.open_input_file(name) as f:
                    raw = f.read_at(min(block, length - k * block), k * block)
                ids = np.frombuffer(raw, "<u2", len(raw) // WIDTH)
                at = np.flatnonzero(ids == eod)
                if len(at):
                    head, tail, inner = int(at[0]), len(ids) - 1 - int(at[-1]), np.diff(at) - 1
                else:
                    head = tail = len(ids)
                    inner = np.zeros(0, np.int64)
                cols = [[file], [k], [len(ids)], [len(at)], [head], [tail]]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(c, pa.string() if i == 0 else pa.int64()) for i, c in enumerate(cols)] + [pa.array([inner], pa.list_(pa.int64()))],
                    ["file", "block", "n_tokens", "n_eod", "head", "tail", "inner"],
                )

    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return cuts.repartition(parts, "file", "block").mapInArrow(lean(run), "file string, block long, n_tokens long, n_eod long, head long, tail long, inner array<long>")


def stitch(blocks: DataFrame) -> DataFrame:
    """(file, ordinal, n_tokens, terminated) of every document, from the block rows; ``blocks`` must be stable when read again."""
    marks = blocks.select("file", "block", "n_eod", "tail", F.floor(F.col("block") / SPAN).alias("span"))
    # The pair (separators, open tokens) of a run of blocks: open tokens restart at the last block with a separator.
    span_last = F.max(F.when(F.col("n_eod") > 0, F.col("block")))
    totals = marks.groupBy("file", "span").agg(F.sum("n_eod").alias("eods"), span_last.alias("last"))
    opened = (
        marks.join(totals.select("file", "span", "last"), ["file", "span"])
        .where(F.col("last").isNull() | (F.col("block") >= F.col("last"))).groupBy("file", "span").agg(F.sum("tail").alias("open"))
    )
    before = Window.partitionBy("file").orderBy("span").rowsBetween(Window.unboundedPreceding, -1)
    # open tokens before a span: the sum of ``open`` since the last span with a separator, that span included
    spans = (
        totals.join(opened, ["file", "span"])
        .withColumn("eods_before", F.coalesce(F.sum("eods").over(before), F.lit(0)))
        .withColumn("_sum", F.coalesce(F.sum("open").over(before), F.lit(0)))
        .withColumn("_cut", F.coalesce(F.max(F.when(F.col("eods") > 0, F.col("_sum"))).over(before), F.lit(0)))
        .withColumn("open_before", F.col("_sum") - F.col("_cut"))
    )
    inside = Window.partitionBy("file", "span").orderBy("block")
    prior = inside.rowsBetween(Window.unboundedPreceding, -1)
    rows = (
        marks.join(spans.select("file", "span", "eods_before", "open_before"), ["file", "span"])
        .withColumn("_done", F.coalesce(F.sum("n_eod").over(prior), F.lit(0)))
        .withColumn("_mark", F.max(F.when(F.col("n_eod") > 0, F.col("block"))).over(prior))
        .withColumn("_sum", F.coalesce(F.sum("tail").over(prior), F.lit(0)))
        .withColumn("_cut", F.coalesce(F.max(F.when(F.col("n_eod") > 0, F.col("_sum"))).over(prior), F.lit(0)))
        .withColumn("open_at", F.col("_sum") - F.col("_cut") + F.when(F.col("_mark").isNull(), F.col("open_before")).otherwise(0))
        .withColumn("first_doc", F.col("eods_before") + F.col("_done"))
        .select("file", "block", "first_doc", "open_at")
    )
    whole = blocks.join(rows, ["file", "block"])
    crossing = whole.where("n_eod > 0").select("file", F.col("first_doc").alias("ordinal"), (F.col("open_at") + F.col("head")).alias("n_tokens"))
    inner = whole.where("n_eod > 1").select("file", "first_doc", F.posexplode("inner").alias("k", "n_tokens")).select("file", (F.col("first_doc") + 1 + F.col("k")).alias("ordinal"), "n_tokens")
    ends = blocks.groupBy("file").agg(F.max("block").alias("block"))
    open_end = F.when(F.col("n_eod") > 0, F.col("tail")).otherwise(F.col("open_at") + F.col("tail"))
    left = whole.join(ends, ["file", "block"]).where(open_end > 0).select("file", (F.col("first_doc") + F.col("n_eod")).alias("ordinal"), open_end.alias("n_tokens"))
    return crossing.union(inner).withColumn("terminated", F.lit(True)).union(left.withColumn("terminated", F.lit(False)))


def count_documents(spark: SparkSession, path: str, eod: int, block: int = BLOCK) -> DataFrame:
    """(file, ordinal, n_tokens, terminated) of every document in the flat token files under ``path``."""
    return stitch(keep(scan_blocks(spark, path, eod, block), "blocks"))


def write_flat(docs: DataFrame, path: str, ranks: str, pattern: str, eod: int) -> DataFrame:
    """Encodes ``docs`` into flat token files under ``path``; returns (file, ordinal, doc_id), which the files themselves don't hold.

    Each task attempt writes files of its own; only those that the returned, written table names count, so what lost
    attempts left is never read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import uuid

        e = bpe.encoder(ranks, pattern)
        store, base = fs.FileSystem.from_uri(path)
        name = f"{base}/{uuid.uuid4().hex}.bin"
        n, out = 0, None
        try:
            for b in small(batches, 4096):
                if out is None:
                    store.create_dir(base, recursive=True)
                    out = store.open_output_stream(name)
                for ids in e.encode_all(b.column(1).to_pylist()):
                    out.write(np.array([*ids, eod], "<u2").tobytes())
                yield pa.RecordBatch.from_arrays(
                    [pa.array([name.rsplit("/", 1)[1]] * b.num_rows), pa.array(np.arange(n, n + b.num_rows)), b.column(0)], ["file", "ordinal", "doc_id"]
                )
                n += b.num_rows
        finally:
            if out is not None:
                out.close()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return keep(rows.mapInArrow(lean(run, bpe.forget_encoders), "file string, ordinal long, doc_id long"), "manifest")


def token_counts(docs: DataFrame, ranks: str, pattern: str, eod: int, block: int = BLOCK) -> DataFrame:
    """(doc_id, file, ordinal, n_tokens) of every row of ``docs``, counted in flat token files written for it.

    Null and empty texts count zero tokens; null and repeated ids are rows of their own.
    """
    spark = docs.sparkSession
    path = scratch(spark, "tokens")
    manifest = write_flat(docs, path, ranks, pattern, eod)
    if manifest.isEmpty():
        return manifest.select("doc_id", "file", "ordinal", F.lit(0).cast("long").alias("n_tokens"))
    counts = count_documents(spark, path, eod, block).where("terminated").withColumn("file", F.regexp_extract("file", r"([^/]+)$", 1))
    return manifest.join(counts, ["file", "ordinal"]).select("doc_id", "file", "ordinal", "n_tokens")
