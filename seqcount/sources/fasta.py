"""FASTA and FASTQ: a reader by record separator, a partitioned data source, a writer."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def read_fasta(spark, path: str) -> DataFrame:
    """(read_id, name, seq) of FASTA files, records of several lines too; read_id is the name's number, else a hash.

    Spark splits files at the record separator, so large files are read in parallel.
    """
    records = spark.read.option("lineSep", ">").text(path).where(F.trim("value") != "")
    name = F.regexp_extract("value", r"^([^\r\n]*)", 1)
    seq = F.upper(F.regexp_replace(F.regexp_replace("value", r"^[^\r\n]*", ""), r"\s", ""))
    number = F.regexp_extract(name, r"^(-?\d+)$", 1)
    return records.select(F.when(number != "", number.cast("long")).otherwise(F.xxhash64(name)).alias("read_id"), name.alias("name"), seq.alias("seq"))


def write_fasta(reads: DataFrame, path: str, width: int = 80, mode: str = "error") -> None:
    """Reads (read_id, seq) as FASTA text files with lines of ``width`` bases."""
    lines = F.regexp_replace("seq", f"(.{{{width}}})(?=.)", "$1\n")
    reads.select(F.concat(F.lit(">"), F.col("read_id").cast("string"), F.lit("\n"), lines).alias("value")).write.mode(mode).text(path)


class _Range(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


class SequenceReader(DataSourceReader):
    """Byte ranges of files; a range owns the records that begin in it."""

    def __init__(self, options: dict):
        self.path, self.size = options["path"], int(options.get("splitBytes", 32 << 20))
        self.kind = options.get("kind", "fastq" if self.path.endswith((".fastq", ".fq")) else "fasta")

    def partitions(self):
        paths = [self.path]
        if os.path.isdir(self.path):
            paths = sorted(os.path.join(self.path, p) for p in os.listdir(self.path) if not p.startswith((".", "_")))
        return [_Range(p, a, min(a + self.size, os.path.getsize(p))) for p in paths for a in range(0, os.path.getsize(p), self.size)]

    def read(self, part):
        records = _fastq if self.kind == "fastq" else _fasta
        with open(part.path, "rb") as f:
            yield from records(f, part.start, part.end)


def _fasta(f, start: int, end: int):
    f.seek(max(0, start - 1))
    if start:
        f.readline()  # the line that the range before owns
    name, body = None, []
    while True:
        at = f.tell()
        line = f.readline()
        if not line or (line.startswith(b">") and at >= end):
            break
        if line.startswith(b">"):
            if name is not None:
                yield name, b"".join(body).decode().upper()
            name, body = line[1:].strip().decode(), []
        elif name is not None:
            body.append(line.strip())
    if name is not None:
        yield name, b"".join(body).decode().upper()


def _fastq(f, start: int, end: int):
    """Records of four lines; a range begins at the first line '@...' that is two lines above a '+...' line."""
    f.seek(max(0, start - 1))
    if start:
        f.readline()
    held: list[tuple[int, bytes]] = []
    while len(held) < 3 or not (held[0][1].startswith(b"@") and held[2][1].startswith(b"+")):
        if len(held) == 3:
            held.pop(0)
        at, line = f.tell(), f.readline()
        if not line:
            return
        held.append((at, line))
    while held and held[0][0] < end:
        yield held[0][1][1:].strip().decode(), held[1][1].strip().decode().upper()
        f.readline()  # qualities
        at = f.tell()
        lines = [f.readline() for _ in range(3)]
        held = [(at, lines[0]), (0, lines[1])] if lines[2] else []


class SequenceFile(DataSource):
    """spark.read.format('seqfile').option('kind', 'fasta' or 'fastq').load(path): (name, seq).

    For paths that the workers can open; ``read_fasta`` reads any store that Spark does.
    """

    @classmethod
    def name(cls) -> str:
        return "seqfile"

    def schema(self) -> str:
        return "name string, seq string"

    def reader(self, schema):
        return SequenceReader(self.options)


def register(spark) -> None:
    spark.dataSource.register(SequenceFile)
