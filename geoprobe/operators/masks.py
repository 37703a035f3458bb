"""Cue masks as a table: detectors by name, one pass over the documents, masks packed to bits.

A detector takes a document's text and gives a boolean mask of its raster; the registry names them, so others can be put in their place."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import workers_can_import
from . import rasters

Detector = Callable[[str], np.ndarray]
REGISTRY: dict[str, Detector] = {cue: partial(rasters.cue_mask, cue=cue) for cue in rasters.CUES}


def packed(mask: np.ndarray) -> bytes:
    return np.packbits(mask).tobytes()


def unpacked(data: bytes, side: int = rasters.SIDE) -> np.ndarray:
    return np.unpackbits(np.frombuffer(data, np.uint8), count=side * side).reshape(side, side).astype(bool)


def detected(docs: DataFrame, registry: dict[str, Detector] | None = None) -> DataFrame:
    """doc_id, cue, mask (packed bits), pixels under it, coverage (their share): every detector on every document (doc_id, text)."""
    workers_can_import(docs.sparkSession)
    known = registry or REGISTRY

    def run(batches):
        for batch in batches:
            out: dict[str, list] = {"doc_id": [], "cue": [], "mask": [], "pixels": [], "coverage": []}
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                for cue, find in known.items():
                    mask = find(text or "")
                    for column, value in zip(out.values(), (doc, cue, packed(mask), int(mask.sum()), float(mask.mean())), strict=True):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(out["doc_id"], pa.int64()), pa.array(out["cue"]), pa.array(out["mask"], pa.binary()), pa.array(out["pixels"], pa.int64()), pa.array(out["coverage"], pa.float64())], names=list(out))

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, cue string, mask binary, pixels long, coverage double")


def write_masks(masks: DataFrame, path: str) -> None:
    """One folder a cue; a rerun replaces the cues that it holds."""
    masks.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("cue").parquet(path)


def mask_sizes(masks: DataFrame) -> DataFrame:
    """Documents, documents with a mask and pixels by cue."""
    return masks.groupBy("cue").agg(F.count("*").alias("n"), F.count_if(F.col("pixels") > 0).alias("with_mask"), F.sum("pixels").alias("pixels"))
