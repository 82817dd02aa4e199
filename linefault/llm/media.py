"""Media columns: texts stored as progressive JPEG, read back into full-resolution RGB tensors and features.

Defined cases: null text is empty and is stored as one group of blanks; equal texts give equal
values; an empty table gives an empty result; broken media raise an error that names the fault, and null media give
null tensors; extra columns are kept by decode_media.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import columns_of, fresh, small_batches, table
from .progressive_jpeg import GROUP, decode_coefficients, encode_payload, read_payload, to_rgb

#: Rows of one Arrow batch, so that decoded tensors in flight stay small.
BATCH = 256


def payload_of(text: bytes | None) -> bytes:
    raw = text or b""
    return raw.ljust(max(GROUP, -(-len(raw) // GROUP) * GROUP), b" ")


def feature(rgb: np.ndarray) -> str:
    """Size, and of each channel the mean, the spread and the share of dark samples."""
    flat = rgb.reshape(-1, 3)
    seen = [np.bincount(flat[:, c], minlength=256) for c in range(3)]
    levels, n = np.arange(256), len(flat)
    means = [float(s @ levels) / n for s in seen]
    spreads = [max(0.0, float(s @ (levels**2)) / n - m * m) ** 0.5 for s, m in zip(seen, means, strict=True)]
    dark = [int(s[:64].sum()) for s in seen]
    return f"{rgb.shape[1]}x{rgb.shape[0]} " + " ".join(f"{m:.4f}:{s:.4f}:{d}" for m, s, d in zip(means, spreads, dark, strict=True))


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, media): each text's bytes as a progressive file."""

    def run(batches):
        for batch in batches:
            texts = [x.as_py() for x in batch["text"]]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array([len(x or b"") for x in texts], pa.int64()), pa.array([encode_payload(payload_of(x)) for x in texts], pa.binary())], ["doc_id", "n_bytes", "media"])

    small_batches(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_bytes long, media binary")


def decode_media(df: DataFrame, media_col: str = "media") -> DataFrame:
    """df with width, height and rgb (height * width * 3 bytes) of its media column; where df has a column of such a name, the
    new one takes an underscore before it."""

    @F.pandas_udf("struct<width:int,height:int,rgb:binary>")
    def decode(media):
        import pandas as pd

        rows = []
        for x in media:
            rgb = None if x is None else to_rgb(decode_coefficients(bytes(x)))
            rows.append((None, None, None) if rgb is None else (rgb.shape[1], rgb.shape[0], rgb.tobytes()))
        return pd.DataFrame(rows, columns=["width", "height", "rgb"])

    small_batches(df.sparkSession)
    held = fresh("decoded_media", df.columns)
    new = [F.col(f"`{held}`.{x}").alias(fresh(x, df.columns)) for x in ("width", "height", "rgb")]
    return df.withColumn(held, decode(F.col(f"`{media_col}`"))).select(*columns_of(df), *new)


def write_tensors(df: DataFrame, path: str, media_col: str = "media") -> DataFrame:
    """The full-resolution tensors of df's media, written as Parquet and read back: df without its media, and width, height,
    rgb. They take about twice the stored bytes."""
    decode_media(df, media_col).drop(media_col).write.parquet(path)
    return df.sparkSession.read.parquet(path)


def as_array(width: int, height: int, rgb: bytes) -> np.ndarray:
    """One stored tensor as (height, width, 3)."""
    return np.frombuffer(rgb, np.uint8).reshape(height, width, 3)


def media_report(stored: DataFrame) -> DataFrame:
    """What the stored bytes give when read back: payload, its digests, and the features of the samples."""

    def run(batches):
        for whole in batches:
            for at in range(0, max(1, whole.num_rows), BATCH):
                batch = whole.slice(at, BATCH)
                rows = []
                for media in batch["media"]:
                    data = media.as_py()
                    image = decode_coefficients(data)
                    payload = read_payload(image)
                    rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(data), hashlib.sha256(data).hexdigest(), feature(to_rgb(image))))
                cols = list(zip(*rows, strict=True)) or [[]] * 6
                kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
                yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["n_bytes"], *[pa.array(c, k) for c, k in zip(cols, kinds, strict=True)]], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    form = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return stored.mapInArrow(run, form)


def op5_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_report(store_texts(table(spark, sf_dir, "documents")))
