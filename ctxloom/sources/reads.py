"""Sources and sinks: read files of sequencers (four-line and header-line formats), JSON lines, CSV, and model tables.

The two text formats are Python data sources whose partitions are whole files or byte ranges moved to record starts, so a
split never cuts a record. Files are opened on executors by their path: they must be on storage that executors mount. For
stores only Spark reaches, :func:`fastq_by_lines` parses lines read by Spark.
"""

from __future__ import annotations

import glob
import os
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ctxloom.operators.stream import Stream, pieces

SPLIT = 64 << 20


class Range(InputPartition):
    def __init__(self, path: str, begin: int, end: int):
        self.path, self.begin, self.end = path, begin, end


class _Splits(DataSourceReader):
    def __init__(self, options):
        self.path, self.split = options["path"], int(options.get("split", SPLIT))

    def partitions(self):
        files = sorted(glob.glob(os.path.join(self.path, "*")) if os.path.isdir(self.path) else glob.glob(self.path))
        return [Range(f, a, min(a + self.split, os.path.getsize(f))) for f in files for a in range(0, max(os.path.getsize(f), 1), self.split)]


class FastqReader(_Splits):
    @staticmethod
    def first_record(f, begin: int) -> int | None:
        """Place of the first record that starts at or after ``begin``: a line with @ two lines before one with +."""
        if not begin:
            return 0
        f.seek(begin - 1)
        f.readline()
        window: list[tuple[int, bytes]] = []
        while True:
            at = f.tell()
            line = f.readline()
            if not line:
                return None
            window = [*window[-2:], (at, line[:1])]
            if [mark for _, mark in window][::2] == [b"@", b"+"] and window[1][1] not in (b"@", b"+"):
                return window[0][0]

    def read(self, part: Range) -> Iterator[tuple]:
        with open(part.path, "rb") as f:
            begin = self.first_record(f, part.begin)
            if begin is None:
                return
            f.seek(begin)
            while f.tell() < part.end:
                head, bases, plus, quality = (f.readline().rstrip(b"\r\n").decode() for _ in range(4))
                if not head:
                    return
                if head[0] != "@" or plus[:1] != "+" or len(bases) != len(quality):
                    raise ValueError(f"not a record in {part.path}: {head[:60]}")
                yield head[1:].split()[0], bases, quality


class FastqSource(DataSource):
    """spark.read.format("fastq").load(path): read_id, bases, quality."""

    @classmethod
    def name(cls) -> str:
        return "fastq"

    def schema(self) -> str:
        return "read_id string, bases string, quality string"

    def reader(self, schema) -> DataSourceReader:
        return FastqReader(self.options)


class FastaReader(_Splits):
    """A sequence comes in chunks of ``chunk`` letters; each carries the last ``halo`` letters before it, so windows across
    chunk borders can be formed: (seq_id, chunk_no, start, halo, bases). One task reads a file."""

    def __init__(self, options):
        super().__init__({**options, "split": str(1 << 60)})
        self.chunk, self.halo = int(options.get("chunk", 1 << 20)), int(options.get("halo", 0))

    def read(self, part: Range) -> Iterator[tuple]:
        name, held, start, number, before = None, [], 0, 0, ""
        size = 0

        def flush(final: bool):
            nonlocal held, start, number, before, size
            text = "".join(held)
            while len(text) >= self.chunk or final and text:
                piece, text = text[: self.chunk], text[self.chunk :]
                yield name, number, start, before, piece
                before = (before + piece)[-self.halo :] if self.halo else ""
                start, number = start + len(piece), number + 1
            held, size = [text] if text else [], len(text)

        with open(part.path, encoding="ascii") as f:
            for line in f:
                line = line.strip()
                if line.startswith(">"):
                    if name is not None:
                        yield from flush(True)
                    name, held, start, number, before, size = line[1:].split()[0], [], 0, 0, "", 0
                elif line:
                    held.append(line)
                    size += len(line)
                    if size >= self.chunk:
                        yield from flush(False)
        if name is not None:
            yield from flush(True)


class FastaSource(DataSource):
    """spark.read.format("fasta").option("chunk", n).option("halo", l).load(path)."""

    @classmethod
    def name(cls) -> str:
        return "fasta"

    def schema(self) -> str:
        return "seq_id string, chunk_no int, start long, halo string, bases string"

    def reader(self, schema) -> DataSourceReader:
        return FastaReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FastqSource)
    spark.dataSource.register(FastaSource)


def fastq_by_lines(spark: SparkSession, path: str) -> DataFrame:
    """read_id, bases, quality through Spark's text reader: lines are numbered within their file's splits by record marks.

    Works for any store; the file must not be split (small files or gzip), as lines are grouped by four in file order.
    """
    lines = spark.read.option("wholetext", False).text(path).select(F.input_file_name().alias("file"), F.monotonically_increasing_id().alias("at"), "value")
    numbered = lines.withColumn("nth", F.row_number().over(Window.partitionBy("file").orderBy("at")) - 1)
    rec = numbered.groupBy("file", F.expr("nth div 4").alias("rec")).agg(F.transform(F.array_sort(F.collect_list(F.struct("nth", "value"))), lambda x: x["value"]).alias("l"))
    return rec.select(F.expr("substring(split(l[0], ' ')[0], 2)").alias("read_id"), F.col("l")[1].alias("bases"), F.col("l")[3].alias("quality"))


def write_fastq(reads: Stream, path: str) -> None:
    """A text stream's reads as four-line records: a base for each letter's class, a score for its code."""
    scores, classes, ids = reads.flat, replace(reads, kind="class", m=4).flat, list(reads.ids)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f, g = scores(batch.column(0)), classes(batch.column(0))
            names = list(zip(*[batch.column(i + 1).to_pylist() for i in range(len(ids))]))
            letters, marks = np.frombuffer(b"ACGT", np.uint8)[g.codes].tobytes().decode(), (f.codes + 33).astype(np.uint8).tobytes().decode()
            values = [f"@{'.'.join(map(str, names[r]))}.{n}\n{letters[a:b]}\n+\n{marks[a:b]}" for r, n, a, b in zip(f.row, f.nth, f.starts[:-1], f.starts[1:])]
            yield pa.RecordBatch.from_arrays([pa.array(values, pa.string())], names=["value"])

    reads.select(*ids).mapInArrow(kernel, "value string").write.text(path)


def read_fastq(spark: SparkSession, path: str) -> DataFrame:
    """read_id, bases, quality of a folder of read files: by record-aligned splits where executors can open it by its path, by
    Spark's own text reader elsewhere."""
    scheme, _, local = path.rpartition("://") if "://" in path else ("file" if path.startswith("file:") else "", "", path.removeprefix("file:"))
    if scheme in ("", "file"):
        register(spark)
        return spark.read.format("fastq").load(f"{local}/part-*")
    return fastq_by_lines(spark, path)


def json_lines(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def csv_rows(spark: SparkSession, path: str, schema: str, header: bool = True) -> DataFrame:
    return spark.read.schema(schema).option("header", header).csv(path)


def quality_codes(quality, offset: int = 33):
    """array<int> of quality scores from their printable letters."""
    return F.transform(F.split(quality, ""), lambda c: F.ascii(c) - offset)


def base_codes(bases):
    """A 0, C 1, G 2, T 3; other letters 0."""
    return F.transform(F.split(F.upper(bases), ""), lambda c: F.greatest(F.instr(F.lit("ACGT"), c) - 1, F.lit(0)))


def save_table(df: DataFrame, path: str, name: str, version: int) -> None:
    """A model, tree, bin table or menu as one version of a named table."""
    df.write.mode("overwrite").parquet(f"{path}/name={name}/version={version}")


def load_table(spark: SparkSession, path: str, name: str, version: int | None = None) -> DataFrame:
    rows = spark.read.parquet(f"{path}/name={name}")
    version = version if version is not None else rows.agg(F.max("version")).first()[0]
    return rows.where(F.col("version") == version).drop("version")
