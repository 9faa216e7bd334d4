"""Token ids as raw binary shards with a minimal perfect hash index.

A shard file holds, one after the other: the ids of its documents (little-endian, unsigned, of 16 bits where the vocabulary fits
them and else 32; in ascending key order, each document closed by the end id), its documents' first positions, their keys, an
index, and a last block of eight numbers that says how much there is of each. The index maps
each distinct key to its place by a minimal perfect hash: on each level a key sets a bit; keys alone on their bit stay, the others
go on to the next level; a key's number is the rank of its bit. Under that number stand a fingerprint of the key, which
rejects foreign keys, the offset of its first row's ids, and how many ids it has. A lookup takes a few bits and one slice, whatever the
shard's size.

Tasks write to names of their own attempt; only what a successful task reports enters the manifest, so a lost executor or a
speculative twin leaves unlisted files at most. Shards are cut by size, so memory doesn't depend on the table.

A null or empty text has only the end id. Rows of a null key come first, are stored, and aren't indexed. Rows that share a key are all
stored, one after the other in the order of a hash of their texts, ties by text; the index leads to the first. Columns beside id and text are ignored. An
empty table gives an empty manifest."""

from __future__ import annotations

import bisect
import uuid
import zlib

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.llm.common import new_path, parts, scramble, spill
from pathtraces.llm.tokens import encoder

END_ID, SHARD_IDS, GAMMA = 2, 1 << 24, 2.0
MAGIC = 0x5054494453303031
_NAMES = ("magic", "rows", "ids", "keys", "levels", "nulls", "bits", "id_bytes")


class PerfectHash:
    """Numbers 0 to n-1 for n distinct 64-bit keys."""

    def __init__(self, sizes: np.ndarray, words: np.ndarray):
        self.sizes, self.words = sizes, words
        self.ranks = np.zeros(len(words) + 1, np.int64)
        np.cumsum(np.bitwise_count(words), out=self.ranks[1:])
        self.starts = np.concatenate([[0], np.cumsum(sizes)])

    @staticmethod
    def _at(keys: np.ndarray, level: int, size: int) -> np.ndarray:
        return (scramble(keys.astype(np.int64).view(np.uint64) + np.uint64(0x9E3779B97F4A7C15 * (level + 1) & (1 << 64) - 1)) % np.uint64(size)).astype(np.int64)

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        sizes, words, left = [], [], keys
        while len(left):
            size = -(-max(64, int(GAMMA * len(left))) // 64) * 64
            at = cls._at(left, len(sizes), size)
            alone = np.bincount(at, minlength=size) == 1
            words.append(np.packbits(alone, bitorder="little").view("<u8"))
            sizes.append(size)
            left = left[~alone[at]]
        return cls(np.array(sizes, np.int64), np.concatenate(words) if words else np.empty(0, "<u8"))

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        """The keys' numbers; -1 for keys that no level holds (others may be foreign all the same)."""
        out, todo = np.full(len(keys), -1, np.int64), np.arange(len(keys))
        for level, size in enumerate(self.sizes):
            if not len(todo):
                break
            at = self._at(keys[todo], level, size) + self.starts[level]
            word, bit = self.words[at >> 6], (at & 63).astype(np.uint64)
            here = (word >> bit & np.uint64(1)).astype(bool)
            below = np.bitwise_count(word & ((np.uint64(1) << bit) - np.uint64(1)))
            out[todo[here]] = (self.ranks[at >> 6] + below)[here]
            todo = todo[~here]
        return out


def key_mark(keys: np.ndarray) -> np.ndarray:
    """The fingerprint stored for a key."""
    return (scramble(keys.astype(np.int64).view(np.uint64) ^ np.uint64(0xA5A5A5A55A5A5A5A)) >> np.uint64(32)).astype("<u4")


class _Shard:
    """A shard as it is written."""

    def __init__(self, filesystem, folder: str, id_bytes: int):
        self.id_bytes = id_bytes
        self.path = f"{folder}/{uuid.uuid4().hex}.ids"
        self.out = filesystem.open_output_stream(self.path)
        self.keys: list[int] = []
        self.sizes: list[int] = []
        self.nulls = self.n = 0

    def add(self, key: int | None, ids: bytes) -> None:
        self.out.write(ids if self.id_bytes == 4 else np.frombuffer(ids, "<u4").astype("<u2").tobytes())
        self.nulls += key is None
        self.keys.append(key or 0)
        self.sizes.append(len(ids) // 4)
        self.n += len(ids) // 4

    def close(self) -> tuple:
        """The index follows the ids, and the numbers stand at the end: stores don't rewrite a file's start."""
        keys, sizes = np.array(self.keys, np.int64), np.array(self.sizes, np.int64)
        starts = np.concatenate([[0], np.cumsum(sizes)])
        own, first = np.unique(keys[self.nulls :], return_index=True)
        first = first + self.nulls
        perfect = PerfectHash.build(own)
        slot = perfect(own)
        mark, offset, length = np.zeros(len(own), "<u4"), np.zeros(len(own), "<i8"), np.zeros(len(own), "<i8")
        mark[slot], offset[slot], length[slot] = key_mark(own), starts[first], sizes[first]
        header = np.array([MAGIC, len(keys), self.n, len(own), len(perfect.sizes), self.nulls, len(perfect.words), self.id_bytes], "<u8")
        for section in (starts.astype("<i8"), keys.astype("<i8"), perfect.sizes.astype("<i8"), perfect.words.astype("<u8"), offset, length, mark, header):
            self.out.write(section.tobytes())
        self.out.close()
        low, high = (int(keys[self.nulls]), int(keys[-1])) if len(own) else (None, None)
        return self.path, len(keys), self.n, low, high


def write_tokens(docs: DataFrame, tokenizer: str, folder: str | None = None, id: str = "doc_id", text: str = "text", end_id: int = END_ID, shard_ids: int = SHARD_IDS) -> DataFrame:
    """Writes the shards to ``folder`` (a new shared one by default); returns the manifest: ``shard`` (0, 1, ... in key order), ``path``,
    ``n_rows``, ``n_ids``, ``low``, ``high`` (keys), ``start`` (ids in all shards before)."""
    spark = docs.sparkSession
    folder = new_path(spark, "tokens") if folder is None else folder
    _filesystem(folder)[0].create_dir(_filesystem(folder)[1], recursive=True)

    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        encode, task = encoder(tokenizer), TaskContext.get().partitionId()
        filesystem, at = _filesystem(folder)
        id_bytes = 2 if max(encode.tokenizer.get_vocab_size(), end_id + 1) <= 1 << 16 else 4
        end, shard, done = np.array([end_id], "<u4").tobytes(), None, []
        for batch in batches:
            for part in parts(batch):
                for key, ids in zip(part.column(0).to_pylist(), encode(part.column(1).to_pylist()), strict=True):
                    shard = shard or _Shard(filesystem, at, id_bytes)
                    shard.add(key, ids + end)
                    if shard.n >= shard_ids:
                        done.append(shard.close())
                        shard = None
        if shard:
            done.append(shard.close())
        rows = [(task, k, *d) for k, d in enumerate(done)]
        cols = list(zip(*rows, strict=True)) or [[]] * 7
        kinds = [pa.int32(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

    names = ["task", "k", "path", "n_rows", "n_ids", "low", "high"]
    keyed = docs.select(F.col(id).cast("long").alias("id"), F.col(text).alias("text"), F.xxhash64(text).alias("h"))
    keyed = keyed.repartitionByRange("id", "h").sortWithinPartitions("id", "h", "text")
    listed = spill(keyed.mapInArrow(run, "task int, k int, path string, n_rows long, n_ids long, low long, high long"), "manifest")
    order = Window.orderBy("task", "k")  # one row a shard of 64 MB
    return listed.select((F.row_number().over(order) - 1).alias("shard"), "path", "n_rows", "n_ids", "low", "high", F.coalesce(F.sum("n_ids").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))


def _filesystem(path: str):
    from pyarrow.fs import FileSystem

    return FileSystem.from_uri(path if "://" in path or path.startswith("/") else path.replace("file:", "", 1))


class ShardReader:
    """One shard: its index in memory, its ids read as asked."""

    def __init__(self, path: str):
        from pyarrow.fs import LocalFileSystem

        filesystem, at = _filesystem(path) if "://" in path else (LocalFileSystem(), path)
        self.file = filesystem.open_input_file(at)
        size, n = self.file.size(), 8 * len(_NAMES)
        self.header = dict(zip(_NAMES, map(int, np.frombuffer(self.file.read_at(n, size - n), "<u8")), strict=True))
        if self.header["magic"] != MAGIC:
            raise ValueError(f"{path} is no token shard, or was cut short")
        self.kind = f"<u{self.header['id_bytes']}"
        at = self.header["id_bytes"] * self.header["ids"]
        tail, self._at = self.file.read_at(size - n - at, at), 0

        def take(kind: str, count: int) -> np.ndarray:
            out = np.frombuffer(tail, kind, count, self._at)
            self._at += out.nbytes
            return out

        h = self.header
        self.starts, self.keys = take("<i8", h["rows"] + 1), take("<i8", h["rows"])
        self.hash = PerfectHash(take("<i8", h["levels"]), take("<u8", h["bits"]))
        self.offset, self.length, self.mark = take("<i8", h["keys"]), take("<i8", h["keys"]), take("<u4", h["keys"])

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Index numbers of keys; -1 where the shard doesn't hold them."""
        slot = self.hash(keys)
        if not self.header["keys"]:
            return slot
        known = (slot >= 0) & (self.mark[np.maximum(slot, 0)] == key_mark(keys))
        return np.where(known, slot, -1)

    def ids(self, offset: int, length: int) -> bytes:
        """As unsigned 32-bit integers."""
        wide = self.header["id_bytes"]
        return np.frombuffer(self.file.read_at(wide * length, wide * offset), self.kind).astype("<u4").tobytes()

    def get(self, key: int) -> np.ndarray | None:
        slot = int(self.find(np.array([key], np.int64))[0])
        return None if slot < 0 else np.frombuffer(self.ids(int(self.offset[slot]), int(self.length[slot])), "<u4")


class TokenStore:
    """Keyed access through a manifest. Holds one row a shard, and the indexes of the shards that were asked."""

    def __init__(self, manifest: DataFrame):
        self.rows = [r for r in manifest.orderBy("shard").collect() if r.low is not None]
        self.highs = [r.high for r in self.rows]
        self.open: dict[str, ShardReader] = {}

    def get(self, key: int) -> np.ndarray | None:
        k = bisect.bisect_left(self.highs, key)
        if k == len(self.rows) or self.rows[k].low > key:
            return None
        path = self.rows[k].path
        if path not in self.open:
            self.open[path] = ShardReader(path)
        return self.open[path].get(key)


def read_tokens(manifest: DataFrame) -> DataFrame:
    """Per stored document, from the files: ``id``, ``start``, ``n_tokens``, ``ids_crc32``. Every key is also looked up in the index,
    and a wrong answer stops the job."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                shard = ShardReader(path)
                nulls, starts, keys = shard.header["nulls"], shard.starts, shard.keys
                own, first = np.unique(keys[nulls:], return_index=True)
                slot = shard.find(own)
                if (slot < 0).any() or (shard.offset[slot] != starts[first + nulls]).any():
                    raise ValueError(f"the index of {path} misses keys")
                for at in range(0, len(keys), 4096):
                    to = min(at + 4096, len(keys))
                    block = shard.ids(int(starts[at]), int(starts[to] - starts[at]))
                    cut = 4 * (starts[at : to + 1] - starts[at])
                    sums = [zlib.crc32(block[a:b]) for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)]
                    yield pa.RecordBatch.from_arrays([pa.array(keys[at:to], mask=np.arange(at, to) < nulls), pa.array(starts[at:to] + start), pa.array(np.diff(starts[at : to + 1])), pa.array(sums, pa.int64())], ["id", "start", "n_tokens", "ids_crc32"])

    shards = manifest.select("path", F.col("start").cast("long"))
    return shards.repartition(max(1, min(shards.count(), 4096))).mapInArrow(run, "id long, start long, n_tokens long, ids_crc32 long")


def token_table(docs: DataFrame, tokenizer: str, id: str = "doc_id", text: str = "text", end_id: int = END_ID) -> DataFrame:
    """Writes the shards, reads them back."""
    return read_tokens(spill(write_tokens(docs, tokenizer, None, id, text, end_id), "manifest")).withColumnRenamed("id", id)

