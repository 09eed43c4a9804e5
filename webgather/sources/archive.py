"""An archive format of compressed records, as a data source to read and write, and two more sources.

A record is a gzip member of its own: headers, an empty line, and the payload. Files are read
whole by one task each, so writers keep them at `roll_bytes` or less.
"""

from __future__ import annotations

import gzip
import io
import os
import uuid
import zlib
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

RECORD = "uri string, date string, status int, payload string"


def encode(uri: str, date: str, status: int, payload: bytes, level: int = 6) -> bytes:
    head = f"WARC/1.0\r\nWARC-Type: response\r\nWARC-Target-URI: {uri}\r\nWARC-Date: {date}\r\nX-Status: {status}\r\nContent-Length: {len(payload)}\r\n\r\n"
    out = io.BytesIO()
    with gzip.GzipFile(fileobj=out, mode="wb", compresslevel=level, mtime=0) as f:
        f.write(head.encode() + payload + b"\r\n\r\n")
    return out.getvalue()


def decode(raw: bytes) -> Iterator[tuple[str, str, int, bytes]]:
    """Records of a file; bytes that aren't a record end it."""
    while raw:
        d = zlib.decompressobj(31)
        try:
            whole = d.decompress(raw) + d.flush()
        except zlib.error:
            return
        raw = d.unused_data
        head, _, body = whole.partition(b"\r\n\r\n")
        fields = dict(line.split(": ", 1) for line in head.decode("utf-8", "replace").split("\r\n")[1:] if ": " in line)
        n = int(fields.get("Content-Length", len(body)))
        yield fields.get("WARC-Target-URI", ""), fields.get("WARC-Date", ""), int(fields.get("X-Status", 0)), body[:n]


class _Written(WriterCommitMessage):
    def __init__(self, names: list[str]):
        self.names = names


class _Writer(DataSourceWriter):
    """Tasks write under a name of their own; commit gives the files their final names."""

    def __init__(self, path: str, roll: int):
        self.path, self.roll = path, roll

    def write(self, rows) -> _Written:
        os.makedirs(self.path, exist_ok=True)
        names: list[str] = []
        out, size = None, 0
        for r in rows:
            if out is None or size >= self.roll:
                if out:
                    out.close()
                names.append(f"part-{uuid.uuid4().hex}.warc.gz")
                out, size = open(os.path.join(self.path, "." + names[-1]), "wb"), 0  # noqa: SIM115
            record = encode(r["uri"] or "", r["date"] or "", r["status"] or 0, (r["payload"] or "").encode("utf-8", "surrogatepass"))
            out.write(record)
            size += len(record)
        if out:
            out.close()
        return _Written(names)

    def commit(self, messages) -> None:
        for m in messages:
            for n in m.names if m else ():
                os.rename(os.path.join(self.path, "." + n), os.path.join(self.path, n))

    def abort(self, messages) -> None:
        for m in messages:
            for n in m.names if m else ():
                os.unlink(os.path.join(self.path, "." + n))


class _File(InputPartition):
    def __init__(self, name: str):
        self.name = name


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        return [_File(os.path.join(self.path, n)) for n in sorted(os.listdir(self.path)) if n.endswith(".warc.gz") and n[0] != "."]

    def read(self, partition):
        with open(partition.name, "rb") as f:
            for uri, date, status, body in decode(f.read()):
                yield uri, date, status, body.decode("utf-8", "replace")


class ArchiveSource(DataSource):
    """spark.read.format("archive").load(path), df.write.format("archive").save(path); the path is one all executors share."""

    @classmethod
    def name(cls) -> str:
        return "archive"

    def schema(self) -> str:
        return RECORD

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])

    def writer(self, schema, overwrite) -> DataSourceWriter:
        return _Writer(self.options["path"], int(self.options.get("roll_bytes", 1 << 30)))


class _Range(InputPartition):
    def __init__(self, a: int, b: int):
        self.a, self.b = a, b


class _WebReader(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.n, self.parts = n, parts

    def partitions(self):
        step = max(1, -(-self.n // self.parts))
        return [_Range(a, min(self.n, a + step)) for a in range(0, self.n, step)]

    def read(self, partition):
        for k in range(partition.a, partition.b):
            yield k, f"http://h{k % 997}.example.com/p{k}"


class SimWebSource(DataSource):
    """URLs of a made-up web without end: options pages and parts."""

    @classmethod
    def name(cls) -> str:
        return "simweb"

    def schema(self) -> str:
        return "n long, url string"

    def reader(self, schema) -> DataSourceReader:
        return _WebReader(int(self.options.get("pages", 1000)), int(self.options.get("parts", 4)))


class _LinkReader(_Reader):
    def partitions(self):
        return [_File(os.path.join(self.path, n)) for n in sorted(os.listdir(self.path)) if n.endswith(".tsv")]

    def read(self, partition):
        with open(partition.name, encoding="utf-8", errors="replace") as f:
            for line in f:
                src, tab, dst = line.rstrip("\n").partition("\t")
                if tab:
                    yield src, dst


class LinkListSource(DataSource):
    """Lines of source, tab, target."""

    @classmethod
    def name(cls) -> str:
        return "linklist"

    def schema(self) -> str:
        return "src string, dst string"

    def reader(self, schema) -> DataSourceReader:
        return _LinkReader(self.options["path"])


def register(spark) -> None:
    for source in (ArchiveSource, SimWebSource, LinkListSource):
        spark.dataSource.register(source)
