"""Media columns kept as content-defined chunks.

A payload is stored as 8-bit mono samples (a RIFF/WAVE file) and cut where a rolling gear hash of
its last 32 bytes has its top bits zero.  Chunks go by digest: joins on digests leave one frame per
digest (the store), a recipe is a medium's ordered list of digests, and joining it with the store
gives the bytes back, which are checked against the medium's SHA-256 before use.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, reliable, table
from .grams import mix, slabs, strings

UNIT, RATE = 64, 8000
#: Chunks: least, most and (a power of two) usual bytes between cuts; compression of a stored frame.
LEAST, MOST, USUAL, LEVEL = 1024, 16384, 4096, 6
_GEAR = (mix(np.arange(1, 257, dtype=np.uint64)) >> np.uint64(32)).astype(np.uint32)


def padded(data: bytes) -> bytes:
    return data + bytes(-len(data) % UNIT if data else UNIT)


def to_media(payload: bytes) -> bytes:
    """A RIFF/WAVE file of unsigned 8-bit mono samples."""
    n = len(payload)
    return b"RIFF" + struct.pack("<I", (36 + n + (n & 1)) & 0xFFFFFFFF) + b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, RATE, RATE, 1, 8) + b"data" + struct.pack("<I", n & 0xFFFFFFFF) + payload + bytes(n & 1)


def from_media(media: bytes) -> bytes:
    """The samples of a stored file; raises ValueError where it isn't one that ``to_media`` wrote."""
    if media[:4] != b"RIFF" or media[8:16] != b"WAVEfmt " or media[36:40] != b"data" or struct.unpack("<HHIIHH", media[20:36]) != (1, 1, RATE, RATE, 1, 8):
        raise ValueError("not an 8-bit mono wave file")
    n = struct.unpack("<I", media[40:44])[0]
    if len(media) != 44 + n + (n & 1):
        raise ValueError("truncated samples")
    return media[44 : 44 + n]


def gear(data: np.ndarray) -> np.ndarray:
    """The gear hash (h = 2 h + value of the byte, 32 bits) after each byte, by doubling its window."""
    h = _GEAR[data]
    for step in (1, 2, 4, 8, 16):
        if len(h) > step:
            h[step:] = h[step:] + (h[:-step] << np.uint32(step))
    return h


def cuts(data: bytes, least: int = LEAST, most: int = MOST, usual: int = USUAL) -> list[int]:
    """Ends of the chunks of ``data``: after a hash whose top bits are zero, within least..most bytes."""
    n, at, out = len(data), 0, []
    marks = np.flatnonzero(gear(np.frombuffer(data, dtype=np.uint8)) < (1 << 32) // usual) + 1 if n > least else np.zeros(0, np.int64)
    while n - at > least:
        i = np.searchsorted(marks, at + least)
        end = min(int(marks[i]) if i < len(marks) else n, at + most, n)
        out.append(end)
        at = end
    return out if at == n and out else [*out, n]


def chunked(data: bytes) -> list[bytes]:
    ends = cuts(data)
    return [data[x:y] for x, y in zip([0, *ends], ends)]


def digest(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


def features(samples: bytes) -> str:
    """Integer features of the samples: count, sum, extremes, crossings of the middle, longest silence unit."""
    x = np.frombuffer(samples, dtype=np.uint8)
    crossings = int(np.count_nonzero((x[1:] >= 128) != (x[:-1] >= 128)))
    energy = int(((x.astype(np.int64) - 128) ** 2).sum())
    return f"samples={len(x)};sum={int(x.sum(dtype=np.int64))};min={int(x.min())};max={int(x.max())};crossings={crossings};energy={energy}"


def _media(batch: pa.RecordBatch) -> Iterator[tuple[int, bytes]]:
    data, offsets = strings(batch.column(1))
    for at, to in slabs(offsets):
        for i in range(at, to):
            yield int(offsets[i + 1] - offsets[i]), to_media(padded(data[offsets[i] : offsets[i + 1]].tobytes()))


def recipes(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media_bytes, media (SHA-256) and the ordered digests of the chunks.

    A null or an empty text is a medium of 64 zero samples; equal texts have equal media; a null
    doc_id stays null and repeated rows give repeated recipes; texts of any length are cut whole; an
    empty table gives an empty result; only doc_id and text are read, so no column clashes.
    """

    def run(batches):
        for batch in batches:
            rows = [(n, len(m), hashlib.sha256(m).digest(), [digest(part) for part in chunked(m)]) for n, m in _media(batch)]
            for i in range(0, len(rows), 2000):
                part = rows[i : i + 2000]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, len(part)), *(pa.array([r[k] for r in part], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.binary()))))], ["doc_id", "n_bytes", "media_bytes", "media", "chunks"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(lean(run), "doc_id long, n_bytes long, media_bytes long, media binary, chunks array<binary>")


def _frames(docs: DataFrame) -> DataFrame:
    """media and the compressed frames of its chunks in order, each medium once per Arrow batch."""

    def run(batches):
        pack = zstandard.ZstdCompressor(level=LEVEL, write_content_size=True, write_checksum=False)
        for batch in batches:
            seen, names, frames, held = set(), [], [], 0
            for _, m in _media(batch):
                if (name := hashlib.sha256(m).digest()) not in seen:
                    seen.add(name)
                    names.append(name)
                    frames.append([pack.compress(part) for part in chunked(m)])
                    held += sum(map(len, frames[-1]))
                if held > 1 << 22:
                    yield pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array(frames, pa.list_(pa.binary()))], ["media", "frames"])
                    names, frames, held = [], [], 0
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array(frames, pa.list_(pa.binary()))], ["media", "frames"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(lean(run), "media binary, frames array<binary>")


def chunk_store(docs: DataFrame, recipe: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The store: each digest's frame once.  (packs, loans, the borrowed places with their digests).

    A digest belongs to the medium that is least among its users.  A pack (media, frames, borrowed)
    holds the frames that its medium owns, null in place of the others, and which digests stand
    there; loans (digest, frame) repeats the owned frames that other media use, so that a rebuild
    moves only shared frames between media.  Only digests travel to find the owners.
    """
    once = recipe.groupBy("media").agg(F.first("chunks").alias("chunks"))
    use = once.select("media", F.posexplode("chunks").alias("at", "digest"))
    owners = use.groupBy("digest").agg(F.min(F.struct("media", "at")).alias("owner"), F.count(F.lit(1)).alias("users")).where("users > 1").select("digest", "owner")
    shared = use.join(owners, "digest", "left").withColumn("owns", (F.col("media") == F.col("owner.media")) & (F.col("at") == F.col("owner.at")))
    # every medium has notes (null owns: used once), so all joins are inner and the frames move once
    notes = shared.groupBy("media").agg(F.collect_list(F.struct("at", "digest", "owns")).alias("notes"))
    held = _frames(docs).groupBy("media").agg(F.first("frames").alias("frames")).join(notes, "media")
    foreign = F.filter("notes", lambda x: ~x["owns"])
    packs = held.select(
        "media", F.transform("frames", lambda f, i: F.when(F.exists(foreign, lambda x: x["at"] == i), F.lit(None)).otherwise(f)).alias("frames"),
        F.map_from_entries(F.transform(foreign, lambda x: F.struct(x["at"], x["digest"]))).alias("borrowed"),
    )
    loans = held.where(F.exists("notes", lambda x: x["owns"])).select("frames", F.explode(F.filter("notes", lambda x: x["owns"])).alias("x")).select(F.col("x.digest").alias("digest"), F.col("frames")[F.col("x.at")].alias("frame"))
    return packs, loans, shared.where(~F.col("owns")).select("media", "at", "digest")


def rebuilt(packs: DataFrame, loans: DataFrame, asked: DataFrame | None = None) -> DataFrame:
    """media, payload_bytes, payload_sha256, tail_crc32 and features of each distinct medium.

    A medium whose bytes do not have its SHA-256 (a chunk is missing or spoiled) raises, which
    fails the job rather than a row.
    """
    if asked is None:
        asked = packs.select("media", F.explode("borrowed").alias("at", "digest"))
    lent = asked.join(loans, "digest").groupBy("media").agg(F.map_from_entries(F.collect_list(F.struct("at", "frame"))).alias("lent"))
    whole = packs.join(lent, "media", "left").select("media", F.transform("frames", lambda f, i: F.coalesce(f, F.col("lent")[i])).alias("frames"))

    def run(batches):
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            rows = []
            for name, frames in zip(batch.column(0).to_pylist(), batch.column(1)):
                media = b"".join(unpack.decompress(f.as_py()) for f in frames if f.is_valid)
                if hashlib.sha256(media).digest() != name:
                    raise ValueError(f"medium {name.hex()} does not have its digest")
                payload = from_media(media)
                rows.append((name, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-UNIT:]), features(payload)))
            kinds = (pa.binary(), pa.int64(), pa.string(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], ["media", "payload_bytes", "payload_sha256", "tail_crc32", "feature"])

    return whole.mapInArrow(lean(run), "media binary, payload_bytes long, payload_sha256 string, tail_crc32 long, feature string")


def write_store(docs: DataFrame, folder: str) -> None:
    """Recipes, packs and loans of ``docs`` as Parquet in a shared folder."""
    recipe = recipes(docs)
    packs, loans, _ = chunk_store(docs, recipe)
    for name, df in (("recipes", recipe), ("packs", packs), ("loans", loans)):
        df.write.mode("overwrite").parquet(f"{folder}/{name}")


def read_store(spark: SparkSession, folder: str) -> DataFrame:
    return rebuilt(spark.read.parquet(f"{folder}/packs"), spark.read.parquet(f"{folder}/loans"))


def op9_media_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text stored as chunked media, read back through the chunk store, verified and described.

    One row for each row of ``documents``, with nulls, empties and repeats as ``recipes`` has them.
    """
    docs = table(spark, sf_dir, "documents")
    recipe = reliable(recipes(docs))
    back = rebuilt(*chunk_store(docs, recipe))
    return recipe.join(back, "media").select(
        "doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", F.lower(F.hex("media")).alias("media_sha256"), "feature", F.size("chunks").alias("n_chunks")
    )
