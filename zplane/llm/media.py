"""Media columns: FLAC streams made from and decoded into PCM, with frame checksums verified."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.session import ship

#: Bytes that are encoded, or decoded, together; they bound the memory of a Python worker.
ENCODE_BYTES, DECODE_BYTES = 1 << 19, 1 << 20


def _groups(column, most: int) -> list[slice]:
    """Slices of a binary column of at most `most` bytes, or one longer row."""
    import numpy as np
    import pyarrow.compute as pc

    out, lo, room = [], 0, 0
    for i, n in enumerate(np.asarray(pc.fill_null(pc.binary_length(column), 0)).tolist()):
        if room and room + n > most:
            out.append(slice(lo, i))
            lo, room = i, 0
        room += n
    if len(column):
        out.append(slice(lo, len(column)))
    return out


def encode_flac(df: DataFrame, data: str = "data", keep: tuple[str, ...] = (), lpc_order: int = 0) -> DataFrame:
    """keep columns + media binary: each row's bytes as an 8-bit mono FLAC stream with a seek table.

    Null data counts as empty (a stream without frames); repeated rows repeat; no shuffle.
    """
    ship(df.sparkSession)
    picked = df.select(*keep, F.col(data).cast("binary").alias("__data"))

    def run(batches):
        import pyarrow as pa

        from zplane.llm import flac_codec, media

        for b in batches:
            for part in media._groups(b.column(b.num_columns - 1), media.ENCODE_BYTES):
                *kept, data = (c.slice(part.start, part.stop - part.start) for c in b.columns)
                streams = flac_codec.encode([x or b"" for x in data.to_pylist()], lpc_order)
                yield pa.RecordBatch.from_arrays([*kept, pa.array(streams, pa.binary())], [*b.schema.names[:-1], "media"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in picked.schema.fields[:-1]), "media binary"])
    return picked.mapInArrow(run, schema)


def decode_flac(df: DataFrame, media: str = "media", keep: tuple[str, ...] = ()) -> DataFrame:
    """keep columns + (media, pcm, n_samples, sample_rate, bits, blocks, error): verified samples of each stream.

    pcm holds the samples as unsigned bytes (up to 8 bits) or little-endian signed 16-bit; blocks holds
    (first_sample, n_samples, byte_offset) of each frame, which is where a reader can seek. A stream that
    breaks the format or fails a CRC or the MD5 has a null pcm and the reason in error. No shuffle.
    """
    ship(df.sparkSession)
    picked = df.select(*keep, F.col(media).cast("binary").alias("media"))

    def run(batches):
        import numpy as np
        import pyarrow as pa

        from zplane.llm import flac_codec
        from zplane.llm import media as m

        block = pa.list_(pa.struct([("first_sample", pa.int64()), ("n_samples", pa.int64()), ("byte_offset", pa.int64())]))
        for b in batches:
            for part in m._groups(b.column(b.num_columns - 1), m.DECODE_BYTES):
                got = flac_codec.decode(b.column(b.num_columns - 1).slice(part.start, part.stop - part.start).to_pylist())
                pcm = [None if "error" in g else ((g["samples"] + 128).astype(np.uint8) if g["info"]["bits"] <= 8 else g["samples"].astype("<i2")).tobytes() for g in got]
                fields = [
                    pa.array(pcm, pa.binary()),
                    pa.array([None if "error" in g else len(g["samples"]) for g in got], pa.int64()),
                    pa.array([None if "error" in g else g["info"]["rate"] for g in got], pa.int32()),
                    pa.array([None if "error" in g else g["info"]["bits"] for g in got], pa.int32()),
                    pa.array([None if "error" in g else [dict(zip(("first_sample", "n_samples", "byte_offset"), x)) for x in g["blocks"]] for g in got], block),
                    pa.array([g.get("error") for g in got], pa.string()),
                ]
                kept = [c.slice(part.start, part.stop - part.start) for c in b.columns]
                yield pa.RecordBatch.from_arrays([*kept, *fields], [*b.schema.names, "pcm", "n_samples", "sample_rate", "bits", "blocks", "error"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in picked.schema.fields), "pcm binary, n_samples long, sample_rate int, bits int, blocks array<struct<first_sample:long,n_samples:long,byte_offset:long>>, error string"])
    return picked.mapInArrow(run, schema)


def pcm_blocks(decoded: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """One row for each frame of what decode_flac gave: keep columns + (first_sample, n_samples, pcm)."""
    width = F.when(F.col("bits") <= 8, 1).otherwise(2)
    rows = decoded.select(*keep, F.explode("blocks").alias("b"), width.alias("w"), F.col("pcm").alias("all"))
    return rows.select(
        *keep,
        F.col("b.first_sample").alias("first_sample"),
        F.col("b.n_samples").alias("n_samples"),
        F.expr("substring(all, cast(b.first_sample * w + 1 as int), cast(b.n_samples * w as int))").alias("pcm"),
    )


def text_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each whole text as padded UTF-8, stored as FLAC, read back and digested.

    Null texts count as empty; the payload is zero-padded to a positive multiple of 64 bytes. Rows whose
    stored form can't be read back raise, since that would mean a lossy column.
    """
    ship(docs.sparkSession)
    raw = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.encode(F.coalesce(F.col(text_col).cast("string"), F.lit("")), "utf-8").alias("raw"))
    sized = raw.select("doc_id", F.octet_length("raw").cast("long").alias("n_bytes"), "raw")
    payload = sized.select("doc_id", "n_bytes", F.expr("concat(raw, unhex(repeat('00', cast(greatest(64, ceil(n_bytes / 64) * 64) - n_bytes as int))))").alias("data"))
    stored = encode_flac(payload, "data", ("doc_id", "n_bytes"))

    def digest(batches):
        import hashlib
        import zlib

        import numpy as np
        import pyarrow as pa

        from zplane.llm import flac_codec
        from zplane.llm import media as m

        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
        for b in batches:
            for part in m._groups(b.column(2), m.DECODE_BYTES):
                doc, n, media = (c.slice(part.start, part.stop - part.start).to_pylist() for c in b.columns)
                rows = []
                for i, got in enumerate(flac_codec.decode(media)):
                    if "error" in got:
                        raise ValueError(f"stored form of {doc[i]} can't be read: {got['error']}")
                    x = got["samples"]
                    pcm = (x + 128).astype(np.uint8).tobytes()
                    zero = int(np.count_nonzero((x[1:] < 0) != (x[:-1] < 0)))
                    feature = f"peak={int(np.abs(x).max())};sum={int(x.sum())};energy={int((x * x).sum())};crossings={zero}"
                    rows.append((doc[i], n[i], len(pcm), hashlib.sha256(pcm).hexdigest(), zlib.crc32(pcm[-64:]), len(media[i]), hashlib.sha256(media[i]).hexdigest(), feature))
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)

    return stored.mapInArrow(
        digest, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    )
