"""Media columns: payloads stored as progressive JPEG, read back, with features of their RGB tensor.

A null or empty text gives one block of zero bytes. Rows are independent; equal
texts give equal media, payloads and features in any batch.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from . import common, progressive

BATCH_BYTES = 2_000_000
OWN = [
    T.StructField("n_bytes", T.LongType()), T.StructField("payload_bytes", T.LongType()), T.StructField("payload_sha256", T.StringType()), T.StructField("tail_crc32", T.LongType()),
    T.StructField("media_bytes", T.LongType()), T.StructField("media_sha256", T.StringType()), T.StructField("feature", T.StringType()),
]
HEAVY = [T.StructField("media", T.BinaryType()), T.StructField("tensor", T.BinaryType()), T.StructField("tensor_shape", T.ArrayType(T.IntegerType()))]


def payload_of(raw: bytes) -> bytes:
    return raw + bytes(64 if not raw else -len(raw) % 64)


def feature_of(tensor: np.ndarray) -> str:
    """Size, channel sums and a four-bin histogram of the first channel."""
    high, wide, _ = tensor.shape
    sums = tensor.sum(axis=(0, 1), dtype=np.int64).tolist()
    bins = np.bincount(tensor[:, :, 0].ravel() >> 6, minlength=4).tolist()
    return f"{wide}x{high};" + ",".join(map(str, sums)) + ";" + ",".join(map(str, bins))


def _rows(raws: list[bytes], heavy: bool):
    files = progressive.encode_payloads([payload_of(r) for r in raws])
    images, coefs = progressive.coefficients(files)
    for raw, file, image in zip(raws, files, images, strict=True):
        back = progressive.stored_payload(image, coefs)
        tensor = progressive.rgb(image, coefs)
        row = (len(raw), len(back), common.sha256_hex(back), zlib.crc32(back[-64:]), len(file), common.sha256_hex(file), feature_of(tensor))
        yield row + ((file, tensor.tobytes(), list(tensor.shape)) if heavy else ())


def media_columns(docs: DataFrame, text: str = "text", tensors: bool = True) -> DataFrame:
    """``docs`` without ``text``, with the payload's figures and, if asked, the JPEG and its full-resolution RGB tensor."""
    from pyspark.sql.pandas.types import to_arrow_schema

    own = OWN + HEAVY * tensors
    rest = docs.drop(*({f.name for f in own} - {text}))
    keep = [c for c in rest.columns if c != text]
    schema = T.StructType([T.StructField(rest.schema[c].name, rest.schema[c].dataType, True) for c in keep] + own)
    arrow = to_arrow_schema(schema)

    def store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        for batch in common.small(batches):
            raws = common.raw_texts(batch, text)
            for a, b in common.slices([len(x) for x in raws], BATCH_BYTES):
                part = batch.slice(a, b - a)
                columns = [part.column(part.schema.get_field_index(c)) for c in keep]
                rows = [*zip(*_rows(raws[a:b], tensors), strict=True)]
                yield pa.RecordBatch.from_arrays([*columns, *(pa.array(v, f.type) for v, f in zip(rows, [*arrow][len(keep) :], strict=True))], schema=arrow)

    return rest.mapInArrow(store, schema)


def decode_column(media: DataFrame, column: str = "media") -> DataFrame:
    """``media`` with ``tensor`` and ``tensor_shape`` of the progressive JPEGs of a binary column; null stays null."""
    from pyspark.sql.pandas.types import to_arrow_schema

    rest = media.drop("tensor", "tensor_shape")
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in rest.schema] + HEAVY[1:])
    arrow = to_arrow_schema(schema)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        for batch in common.small(batches):
            files = batch.column(batch.schema.get_field_index(column)).to_pylist()
            for a, b in common.slices([len(x or b"") for x in files], BATCH_BYTES):
                have = [f for f in files[a:b] if f is not None]
                images, coefs = progressive.coefficients(have)
                found = iter([progressive.rgb(i, coefs) for i in images])
                tensors = [None if f is None else next(found) for f in files[a:b]]
                part = batch.slice(a, b - a)
                values = [pa.array([None if t is None else t.tobytes() for t in tensors], pa.binary()), pa.array([None if t is None else list(t.shape) for t in tensors], pa.list_(pa.int32()))]
                yield pa.RecordBatch.from_arrays([*part.columns, *values], schema=arrow)

    return rest.mapInArrow(read, schema)


def query(spark, sf_dir: str) -> DataFrame:
    docs = common.load(spark, sf_dir, "documents").select("doc_id", "text")
    return media_columns(docs, tensors=False)


ORACLE = None
"""SQL has no image codec; tests hold payloads, crc and decoded samples against direct computation."""
