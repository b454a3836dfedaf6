"""FASTA files: a batch reader and writer as a Python data source, a stream reader, and plain functions.

Headers start with ``>``; lines with ``;`` are comments; blank lines, CRLF and lower case are accepted; an item may be
empty. Large files are read in byte ranges, each starting at the first header in it, so one file feeds many tasks.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, DataSourceWriter, EqualTo, InputPartition, WriterCommitMessage

from seqvault.operators.shared_fs import resolve

SCHEMA = "seq_id string, seq string"
#: Bytes of a partition of one file.
PART_BYTES = 32 << 20


def parse(lines: Iterator[str], upper: bool = True) -> Iterator[tuple[str, str]]:
    """(name, sequence) of each record; text before the first header is ignored."""
    name, parts = None, []
    for line in lines:
        line = line.strip()
        if not line or line[0] == ";":
            continue
        if line[0] == ">":
            if name is not None:
                yield name, "".join(parts)
            name, parts = line[1:].split(" ")[0], []
        elif name is not None:
            parts.append(line.upper() if upper else line)
    if name is not None:
        yield name, "".join(parts)


def files_of(path: str) -> list[tuple[str, int]]:
    store, root = resolve(path)
    info = store.get_file_info(root)
    if info.type == fs.FileType.File:
        return [(root, info.size)]
    found = store.get_file_info(fs.FileSelector(root, recursive=True, allow_not_found=True))
    return sorted((f.path, f.size) for f in found if f.type == fs.FileType.File and f.base_name.endswith((".fa", ".fasta", ".fna")))


class ByteRange(InputPartition):
    def __init__(self, path: str, low: int, high: int):
        self.path, self.low, self.high = path, low, high


def range_lines(store: fs.FileSystem, part: ByteRange) -> Iterator[str]:
    """Lines from the first header that starts in the range up to the first header at or after its end."""
    with store.open_input_file(part.path) as raw:
        at, rest, started = part.low, b"", False
        if part.low:
            raw.seek(part.low - 1)
            at -= 1
        else:
            raw.seek(0)
        offset = at
        skip_first = part.low > 0
        while True:
            chunk = raw.read(1 << 20)
            rest += chunk
            lines = rest.split(b"\n")
            rest = lines.pop() if chunk else b""
            for line in lines:
                begin, offset = offset, offset + len(line) + 1
                if skip_first:  # the line that holds the byte before the range belongs to the range before
                    skip_first = False
                    continue
                header = line.startswith(b">")
                if header and begin >= part.high:
                    return
                started = started or header
                if started:
                    yield line.decode()
            if not chunk:
                return


class FastaReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.size = options["path"], int(options.get("partbytes", PART_BYTES))
        self.upper = options.get("upper", "true") == "true"
        self.wanted: set[str] = set()

    def partitions(self) -> list[ByteRange]:
        return [ByteRange(p, low, min(low + self.size, size)) for p, size in files_of(self.path) for low in range(0, max(size, 1), self.size)]

    def read(self, partition: ByteRange) -> Iterator[tuple[str, str]]:
        store, _ = resolve(self.path)
        for name, seq in parse(range_lines(store, partition), self.upper):
            if not self.wanted or {name} == self.wanted:
                yield name, seq


class PushingFastaReader(FastaReader):
    """Takes over equality on the name; used where Spark allows filters to reach Python sources (off by default)."""

    def pushFilters(self, filters):  # noqa: N802
        """Equality on the name is taken over by the reader."""
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("seq_id",):
                self.wanted.add(f.value)
            else:
                yield f


class FastaStreamReader(DataSourceStreamReader):
    """New files since the last offset; a file is whole in one batch."""

    def __init__(self, options: dict):
        self.options = options

    def initialOffset(self) -> dict:  # noqa: N802
        return {"seen": 0}

    def latestOffset(self) -> dict:  # noqa: N802
        return {"seen": len(files_of(self.options["path"]))}

    def partitions(self, start: dict, end: dict) -> list[ByteRange]:
        return [ByteRange(p, 0, size) for p, size in files_of(self.options["path"])[start["seen"] : end["seen"]]]

    def read(self, partition: ByteRange) -> Iterator[tuple[str, str]]:
        yield from FastaReader(self.options).read(partition)


class FastaMessage(WriterCommitMessage):
    def __init__(self, path: str | None):
        self.path = path


class FastaWriter(DataSourceWriter):
    """One file per task, written under a hidden name and renamed at the commit of the whole job."""

    def __init__(self, options: dict):
        self.path, self.width = options["path"], int(options.get("width", 60))

    def write(self, rows) -> FastaMessage:
        store, root = resolve(self.path)
        store.create_dir(root, recursive=True)
        path, n = f"{root}/_part-{uuid.uuid4().hex[:12]}.tmp", 0
        with store.open_output_stream(path) as out:
            for row in rows:
                n += 1
                seq = row["seq"]
                lines = [seq[i : i + self.width] for i in range(0, len(seq), self.width)]
                out.write("\n".join([f">{row['seq_id']}", *lines, ""]).encode())
        if not n:
            store.delete_file(path)
        return FastaMessage(path if n else None)

    def commit(self, messages: list[FastaMessage]) -> None:
        store, _ = resolve(self.path)
        for m in messages:
            if m and m.path:
                folder, _, name = m.path.rpartition("/")
                store.move(m.path, f"{folder}/{name[1:-4]}.fa")

    def abort(self, messages: list[FastaMessage]) -> None:
        store, _ = resolve(self.path)
        for m in messages:
            if m and m.path:
                store.delete_file(m.path)


class FastaSource(DataSource):
    """``spark.read.format("fasta").load(path)``; options partbytes, upper, pushdown, and width for writing."""

    @classmethod
    def name(cls) -> str:
        return "fasta"

    def schema(self) -> str:
        return SCHEMA

    def _options(self) -> dict:
        return dict(self.options)

    def reader(self, schema) -> FastaReader:
        options = self._options()
        return (PushingFastaReader if options.get("pushdown") == "true" else FastaReader)(options)

    def streamReader(self, schema) -> FastaStreamReader:  # noqa: N802
        return FastaStreamReader(self._options())

    def writer(self, schema, overwrite: bool) -> FastaWriter:
        return FastaWriter(self._options())


def read_fasta(spark: SparkSession, path: str, **options) -> DataFrame:
    """seq_id, seq of a file or folder."""
    spark.dataSource.register(FastaSource)
    allowed = spark.conf.get("spark.sql.python.filterPushdown.enabled", "false")
    return spark.read.format("fasta").options(pushdown=allowed, **options).load(path)


def write_fasta(items: DataFrame, path: str, width: int = 60) -> None:
    items.sparkSession.dataSource.register(FastaSource)
    items.select("seq_id", "seq").write.format("fasta").mode("append").option("width", str(width)).save(path)


