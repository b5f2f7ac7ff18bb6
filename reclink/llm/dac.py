"""Token-id output in directly addressable codes.

An id is cut into chunks of `chunk_bits`, lowest first.  Level 0 holds the first chunk of
every id, level 1 the second chunk of those that have one, and so on.  A continuation
bitmap per level tells which ids go on, and a rank directory (set bits before each
512-bit block) finds the place on the next level, so any id is read without decoding
others.

A shard file holds the texts of one range of doc_id as segments, then a directory of the
segments.  Shards are written in ascending doc_id order (null first; equal ids by the
hash of their text), each under a temporary name that is renamed when whole, and only
shards named by the manifest are read, so lost or repeated tasks do no harm.

Null or empty texts give the end id alone.  Empty tables give no shard and no row.
Further columns, whatever their names, are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.llm._common import AtomicWriter, SharedFile, fresh_uri, materialise, text_steps, tidy, worker_cache
from reclink.llm._tokens import ChunkEncoder, tokenizer_path

MAGIC = b"DACSHARD1\n"
RANK_BITS = 512
SEGMENT_TOKENS = 1 << 20


# ---------------------------------------------------------------- the code
def encode(ids: np.ndarray, chunk_bits: int = 8) -> bytes:
    """ids (unsigned 32-bit) as directly addressable codes; chunks of 8 or 16 bits."""
    kind = {8: np.uint8, 16: np.uint16}[chunk_bits]
    rest, parts = np.asarray(ids, np.uint32), []
    while True:
        more = rest >= (1 << chunk_bits)
        chunks = (rest & ((1 << chunk_bits) - 1)).astype(kind)
        bits = np.packbits(more, bitorder="little")
        pad = -len(bits) % (RANK_BITS // 8)
        words = np.concatenate([bits, np.zeros(pad, np.uint8)]).reshape(-1, RANK_BITS // 8)
        ones = np.bitwise_count(words).sum(axis=1, dtype=np.int64)
        ranks = (np.cumsum(ones) - ones).astype("<u4")
        parts.append(struct.pack("<QQQ", len(chunks), len(bits), len(ranks)) + chunks.astype(f"<u{chunk_bits // 8}").tobytes() + bits.tobytes() + ranks.tobytes())
        if not more.any():
            break
        rest = rest[more] >> chunk_bits
    return struct.pack("<BB", chunk_bits, len(parts)) + b"".join(parts)


class Codes:
    """Reads codes in place: `codes[i]` one id, `codes.all()` every id."""

    def __init__(self, buffer: bytes):
        self.bits, levels = struct.unpack_from("<BB", buffer)
        at, self.levels = 2, []
        for _ in range(levels):
            n, flag_bytes, n_ranks = struct.unpack_from("<QQQ", buffer, at)
            at += 24
            chunks = np.frombuffer(buffer, f"<u{self.bits // 8}", n, at)
            at += chunks.nbytes
            flags = np.frombuffer(buffer, np.uint8, flag_bytes, at)
            at += flag_bytes
            ranks = np.frombuffer(buffer, "<u4", n_ranks, at)
            at += ranks.nbytes
            self.levels.append((chunks, flags, ranks))

    def __len__(self) -> int:
        return len(self.levels[0][0])

    def __getitem__(self, i: int) -> int:
        if not 0 <= i < len(self):
            raise IndexError(i)
        value = 0
        for depth, (chunks, flags, ranks) in enumerate(self.levels):
            value |= int(chunks[i]) << (self.bits * depth)
            byte, bit = divmod(i, 8)
            if not flags[byte] >> bit & 1:
                break
            block = i // RANK_BITS
            before = flags[block * (RANK_BITS // 8) : byte]
            i = int(ranks[block]) + int(np.bitwise_count(before).sum()) + int(flags[byte] & ((1 << bit) - 1)).bit_count()
        return value

    def all(self) -> np.ndarray:
        out = self.levels[0][0].astype(np.uint32)
        live = np.arange(len(out))
        for depth in range(1, len(self.levels)):
            flags = np.unpackbits(self.levels[depth - 1][1], bitorder="little")[: len(live)].astype(bool)
            live = live[flags]
            out[live] |= self.levels[depth][0].astype(np.uint32) << (self.bits * depth)
        return out


# ---------------------------------------------------------------- shard files
class ShardWriter:
    """Segments of texts: (ids of the texts, null flags, tokens of each), then codes."""

    def __init__(self, uri: str, chunk_bits: int = 8):
        self.out, self.chunk_bits = AtomicWriter(uri), chunk_bits
        self.out.write(MAGIC)
        self.directory: list[tuple[int, int, int, int, int]] = []
        self.tokens = self.texts = 0

    def segment(self, doc_ids: np.ndarray, is_null: np.ndarray, sizes: np.ndarray, ids: np.ndarray) -> None:
        at = self.out.position
        body = encode(ids, self.chunk_bits)
        head = np.asarray(doc_ids, "<i8").tobytes() + np.asarray(is_null, np.uint8).tobytes() + np.asarray(sizes, "<u8").tobytes()
        self.out.write(head + body)
        self.directory.append((at, self.tokens, len(ids), len(sizes), self.out.position - at))
        self.tokens += len(ids)
        self.texts += len(sizes)

    def close(self) -> None:
        at = self.out.position
        self.out.write(np.array(self.directory, "<u8").reshape(-1, 5).tobytes())
        self.out.write(struct.pack("<QQ", at, len(self.directory)) + MAGIC)
        self.out.commit()


class ShardReader:
    """A shard file: `token(i)` reads one id; `segments()` yields whole segments."""

    def __init__(self, uri: str):
        self.file = SharedFile(uri)
        tail = self.file.read_at(self.file.size - 16 - len(MAGIC), 16 + len(MAGIC))
        if tail[16:] != MAGIC:
            raise ValueError(f"{uri} is no complete shard")
        at, n = struct.unpack_from("<QQ", tail)
        self.directory = np.frombuffer(self.file.read_at(at, n * 40), "<u8").reshape(-1, 5).astype(np.int64)
        self._open: tuple[int, Codes] | None = None

    def _codes(self, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, Codes]:
        at, _, _, texts, length = self.directory[k].tolist()
        raw = self.file.read_at(at, length)
        return np.frombuffer(raw, "<i8", texts), np.frombuffer(raw, np.uint8, texts, 8 * texts), np.frombuffer(raw, "<u8", texts, 9 * texts).astype(np.int64), Codes(raw[17 * texts :])

    def token(self, i: int) -> int:
        k = int(np.searchsorted(self.directory[:, 1], i, "right")) - 1
        if self._open is None or self._open[0] != k:
            self._open = (k, self._codes(k)[3])
        return self._open[1][i - int(self.directory[k, 1])]

    def segments(self) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, Codes]]:
        for k in range(len(self.directory)):
            yield int(self.directory[k, 1]), *self._codes(k)


# ---------------------------------------------------------------- Spark
def write_shards(docs: DataFrame, folder: str, path: str, end_id: int = 2, spaced: bool = False, chunk_bits: int = 8) -> DataFrame:
    """Encode all texts and write shard files under folder; returns the manifest, written
    too: part (ascending with doc_id), uri, n_docs, n_tokens."""

    def encode_part(batches):
        from pyspark import TaskContext

        store = worker_cache()
        if ("encoder", path) not in store:
            store["encoder", path] = ChunkEncoder(path, spaced)
        encoder, shard = store["encoder", path], None
        part = TaskContext.get().partitionId()
        uri = f"{folder}/shard-{part:06d}.dac"
        held: list[tuple] = []

        def flush():
            shard.segment(*(np.concatenate(x) for x in zip(*held)))
            held.clear()

        for batch in batches:
            names = batch.column(0)
            for at, to, data, offsets in text_steps(batch.column(1), 2 << 20):
                ids, sizes = encoder.encode(data, offsets)
                ends = np.cumsum(sizes)
                ids = np.insert(ids, ends, np.uint32(end_id))
                rows = names.slice(at, to - at)
                shard = shard or ShardWriter(uri, chunk_bits)
                held.append((rows.fill_null(0).to_numpy(zero_copy_only=False), rows.is_null().to_numpy(zero_copy_only=False), sizes + 1, ids))
                if sum(len(x[3]) for x in held) >= SEGMENT_TOKENS:
                    flush()
        if shard:
            if held:
                flush()
            shard.close()
            encoder.release()
            yield pa.RecordBatch.from_pylist([{"part": part, "uri": uri, "n_docs": shard.texts, "n_tokens": shard.tokens}], schema=pa.schema([("part", pa.int64()), ("uri", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())]))

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text"))
    rows = rows.withColumn("tie", F.xxhash64("text"))
    ordered = rows.repartitionByRange("doc_id", "tie").sortWithinPartitions("doc_id", "tie").select("doc_id", "text")
    return materialise(ordered.mapInArrow(tidy(encode_part), "part long, uri string, n_docs long, n_tokens long"), "dac-manifest")


def read_shards(manifest: DataFrame) -> DataFrame:
    """Per text of the shards: doc_id, start, n_tokens, ids_crc32.  The manifest has one
    row per written partition, so the driver can sum up where each shard begins."""
    spark = manifest.sparkSession
    shards, start = [], 0
    for row in manifest.orderBy("part").collect():
        shards.append((row["uri"], start))
        start += row["n_tokens"]

    def read_part(batches):
        kind = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])
        for batch in batches:
            for uri, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                for first, names, is_null, sizes, codes in ShardReader(uri).segments():
                    ids = codes.all().astype("<u4")
                    stops = np.cumsum(sizes)
                    begins = stops - sizes
                    view = memoryview(ids.tobytes())
                    sums = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(begins.tolist(), stops.tolist())]
                    yield pa.RecordBatch.from_arrays([pa.array(names, mask=is_null.astype(bool)), pa.array(base + first + begins), pa.array(sizes), pa.array(sums, pa.int64())], schema=kind)

    frame = spark.createDataFrame(shards, "uri string, start long")
    if shards:
        frame = frame.repartition(min(len(shards), 4096))
    return frame.mapInArrow(tidy(read_part), "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_file(docs: DataFrame, path: str | None = None, end_id: int = 2) -> DataFrame:
    """Write docs (doc_id, text) as shard files in the shared folder and read them back."""
    path = path or tokenizer_path("word_bpe_49k.json")
    return read_shards(write_shards(docs, fresh_uri(docs.sparkSession, "dac"), path, end_id))
