"""Data source `segpool`: pool files as raw bytes.

A file is the segments of one shard in address order: next address (8 bytes, -1 at the end), then length-prefixed
blocks. Reading gives (shard, addr, next_addr, d_block, f_block, p_blocks); a directory of files is a pool. Each file
is read in extents, cut where segments start, which a small index beside it (.idx) names.
"""

from __future__ import annotations

import os
import struct
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

SCHEMA = "shard int, addr long, next_addr long, d_block binary, f_block binary, p_blocks array<binary>"
EXTENT = 16 << 20


def pack(next_addr: int | None, d: bytes, f: bytes, p: list[bytes]) -> bytes:
    body = [struct.pack("<q", -1 if next_addr is None else next_addr)]
    for block in (d, f, *p):
        body += [struct.pack("<I", len(block)), block]
    return b"".join(body)


def unpack(data: bytes) -> tuple[int | None, bytes, bytes, list[bytes]]:
    nxt, at, blocks = struct.unpack_from("<q", data)[0], 8, []
    while at < len(data):
        n = struct.unpack_from("<I", data, at)[0]
        blocks.append(data[at + 4 : at + 4 + n])
        at += 4 + n
    return None if nxt < 0 else nxt, blocks[0], blocks[1], blocks[2:]


class Extent(InputPartition):
    def __init__(self, path: str, shard: int, starts: list[int], end: int):
        self.path, self.shard, self.starts, self.end = path, shard, starts, end


@dataclass
class Written(WriterCommitMessage):
    files: list[str]


class PoolReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        out = []
        for name in sorted(os.listdir(self.path)):
            if not name.endswith(".pool"):
                continue
            file = os.path.join(self.path, name)
            with open(file[:-5] + ".idx", "rb") as f:
                raw = f.read()
            starts = list(struct.unpack(f"<{len(raw) // 8}q", raw))
            size, first = os.path.getsize(file), 0
            for i in range(1, len(starts) + 1):
                if i == len(starts) or starts[i] - starts[first] >= EXTENT:
                    out.append(Extent(file, int(name.split("-")[1]), starts[first:i], starts[i] if i < len(starts) else size))
                    first = i
        return out or [None]

    def read(self, extent) -> Iterator[tuple]:
        if extent is None:
            return
        with open(extent.path, "rb") as f:
            f.seek(extent.starts[0])
            data = f.read(extent.end - extent.starts[0])
        base = extent.starts[0]
        for start, end in zip(extent.starts, [*extent.starts[1:], extent.end]):
            nxt, d, fr, p = unpack(data[start - base : end - base])
            yield extent.shard, start, nxt, d, fr, p


class PoolWriter(DataSourceWriter):
    """Rows of a shard must come together and in address order; a task writes a file for each shard it has."""

    def __init__(self, path: str):
        self.path = path

    def write(self, rows) -> Written:
        os.makedirs(self.path, exist_ok=True)
        files, shard, out, starts, at = [], None, None, [], 0

        def close() -> None:
            if out:
                out.close()
                with open(files[-1][:-5] + ".idx", "wb") as f:
                    f.write(struct.pack(f"<{len(starts)}q", *starts))

        for r in rows:
            if r.shard != shard:
                close()
                shard, starts, at = r.shard, [], 0
                files.append(os.path.join(self.path, f"shard-{shard}-.pool"))
                out = open(files[-1], "wb")  # noqa: SIM115
            data = pack(r.next_addr, r.d_block, r.f_block, r.p_blocks)
            if r.addr != at:
                raise ValueError(f"segment at {r.addr}, pool end is {at}: rows must be in address order, without holes")
            starts.append(at)
            out.write(data)
            at += len(data)
        close()
        return Written(files)

    def commit(self, messages) -> None:
        pass

    def abort(self, messages) -> None:
        for m in messages:
            for f in m.files if m else []:
                os.remove(f)


class SegmentPool(DataSource):
    """spark.dataSource.register(SegmentPool); spark.read.format("segpool").load(path). The path is a mounted folder
    that executors share; pools in other stores are kept as Parquet by `io.write_segments`."""

    @classmethod
    def name(cls) -> str:
        return "segpool"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> PoolReader:
        return PoolReader(self.options["path"])

    def writer(self, schema, overwrite) -> PoolWriter:
        return PoolWriter(self.options["path"])
