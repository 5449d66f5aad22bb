"""Words of the training-data operators, runs of bytes other than 0x20 and 0x09-0x0D, and maps over blocks of whole texts."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.functions.shingles import SPACE, Words, buffer_of, mix, set_key, shingle_sets, text_blocks

WORD = r"[^\x20\x09-\x0D]+"
_SPACE = np.zeros(256, bool)
_SPACE[list(SPACE)] = True

__all__ = ["WORD", "Words", "buffer_of", "mix", "set_key", "shingle_sets", "text_blocks", "text_map"]


def text_map(df: DataFrame, text: str, keep: list[str], fields: list[T.StructField], fn: Callable[[pa.Array], list[pa.Array]], most: int = 2 << 20) -> DataFrame:
    """``keep`` columns of ``df`` and one value per row for each of ``fields``, from ``fn`` over blocks of whole texts.

    A block has at most ``most`` bytes (or one text), so memory follows the longest text, not the batch.
    """
    src = df.select(*keep, F.col(text).alias("_text"))
    schema = T.StructType([*df.select(*keep).schema.fields, *fields])
    names = [f.name for f in schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in text_blocks(batch, "_text", most):
                part = batch.slice(a, b - a)
                made = fn(part.column(len(keep)))
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keep))), *made], names=names)

    return src.mapInArrow(run, schema)
