"""Small files of the driver on whatever file system the shared folder is on, and a cache of their blocks."""

from __future__ import annotations

from collections import OrderedDict

from pyspark.sql import SparkSession


class Files:
    """Reading, writing, listing and deleting by the session's own file systems."""

    def __init__(self, spark: SparkSession):
        self.jvm, self.conf = spark._jvm, spark._jsparkSession.sessionState().newHadoopConf()

    def _at(self, path: str):
        place = self.jvm.org.apache.hadoop.fs.Path(path)
        return place.getFileSystem(self.conf), place

    def names(self, path: str) -> list[str]:
        fs, place = self._at(path)
        return sorted(s.getPath().getName() for s in fs.listStatus(place)) if fs.exists(place) else []

    def write(self, path: str, text: str | bytes) -> None:
        """A new file is written aside and then takes the place of the old one."""
        fs, place = self._at(path)
        aside = self.jvm.org.apache.hadoop.fs.Path(path + ".new")
        out = fs.create(aside, True)
        try:
            out.write(bytearray(text.encode() if isinstance(text, str) else text))
        finally:
            out.close()
        fs.delete(place, False)
        if not fs.rename(aside, place):
            raise OSError(f"can't write {path}")

    def read_bytes(self, path: str, at: int = 0, size: int | None = None) -> bytes:
        fs, place = self._at(path)
        length = fs.getFileStatus(place).getLen()
        size = max(0, min(length - at, length if size is None else size))
        stream = fs.open(place)
        try:
            stream.seek(at)
            return bytes(stream.readNBytes(size))
        finally:
            stream.close()

    def read(self, path: str) -> str:
        return self.read_bytes(path).decode()

    def length(self, path: str) -> int:
        fs, place = self._at(path)
        return fs.getFileStatus(place).getLen()

    def delete(self, path: str) -> None:
        fs, place = self._at(path)
        fs.delete(place, True)


class BlockCache:
    """Byte ranges of files through blocks of a fixed size, the least recently used of which go first."""

    def __init__(self, files: Files, block: int = 1 << 16, keep: int = 256):
        self.files, self.block, self.keep = files, block, keep
        self.held: OrderedDict[tuple[str, int], bytes] = OrderedDict()
        self.hits = self.reads = 0

    def _get(self, path: str, k: int) -> bytes:
        self.reads += 1
        key = (path, k)
        if key in self.held:
            self.hits += 1
            self.held.move_to_end(key)
            return self.held[key]
        data = self.held[key] = self.files.read_bytes(path, k * self.block, self.block)
        if len(self.held) > self.keep:
            self.held.popitem(last=False)
        return data

    def read(self, path: str, at: int, size: int) -> bytes:
        if size <= 0:
            return b""
        first, last = at // self.block, (at + size - 1) // self.block
        data = b"".join(self._get(path, k) for k in range(first, last + 1))
        return data[at - first * self.block :][:size]


class ClipFile:
    """A clip's GOPs laid end to end in one file, with an index of (GOP, offset, size): what a host reads segments from."""

    def __init__(self, cache: BlockCache, path: str):
        self.cache, self.path = cache, path
        import json

        self.index = {int(k): tuple(v) for k, v in json.loads(cache.files.read(path + ".index")).items()}

    @staticmethod
    def write(files: Files, path: str, gops: list[dict]) -> None:
        """``gops``: the rows (gop_id, packets) of one clip; a clip beyond a host's memory is written as several files."""
        import json
        import pickle

        blobs, index, at = [], {}, 0
        for g in sorted(gops, key=lambda g: g["gop_id"]):
            blob = pickle.dumps([(p["dpos"], p["idx"], p["kind"], bytes(p["bytes"])) for p in g["packets"]])
            index[g["gop_id"]] = (at, len(blob))
            blobs.append(blob)
            at += len(blob)
        files.write(path, b"".join(blobs))
        files.write(path + ".index", json.dumps(index))

    def packets(self, gop_id: int) -> list[dict]:
        import pickle

        at, size = self.index[gop_id]
        return [dict(zip(("dpos", "idx", "kind", "bytes"), p, strict=True)) for p in pickle.loads(self.cache.read(self.path, at, size))]  # noqa: S301  our own file
