"""Models as operators: what annotates, judges, compares, translates, generates, segments, detects, embeds, re-ranks or
scores is one call from input columns to an output column.

An ExpressionModel is a deterministic stand-in that stays in the JVM. An ArrowModel carries a real model: `load` runs once
in each worker process, `call` takes the input columns of a slice of rows and gives the output column.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass
from typing import Any, Protocol

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import StructField, StructType, _parse_datatype_string


class Model(Protocol):
    """apply() adds a column to a table; rows, their order within a partition and all other columns stay."""

    def apply(self, df: DataFrame, in_cols: Sequence[str], out_col: str) -> DataFrame: ...


@dataclass(frozen=True)
class ExpressionModel:
    expression: Callable[..., Column]

    def apply(self, df: DataFrame, in_cols: Sequence[str], out_col: str) -> DataFrame:
        return df.withColumn(out_col, self.expression(*(F.col(c) for c in in_cols)))


_LOADED: dict[str, Any] = {}


@dataclass(frozen=True)
class ArrowModel:
    name: str
    load: Callable[[], Any]
    call: Callable[..., list]
    out_type: str
    rows: int = 256

    def apply(self, df: DataFrame, in_cols: Sequence[str], out_col: str) -> DataFrame:
        name, load, call, rows, names = self.name, self.load, self.call, self.rows, [*df.columns, out_col]
        kind = _parse_datatype_string(self.out_type)
        schema, arrow = StructType([*df.schema.fields, StructField(out_col, kind)]), to_arrow_type(kind)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            from textmill.functions import protocols as own

            if name not in own._LOADED:
                own._LOADED[name] = load()
            for batch in batches:
                for at in range(0, batch.num_rows, rows):
                    part = batch.slice(at, rows)
                    out = call(own._LOADED[name], *(part.column(c).to_pylist() for c in in_cols))
                    yield pa.RecordBatch.from_arrays([*part.columns, pa.array(out, arrow)], names=names)

        return df.mapInArrow(run, schema)


#: Roles; each is a Model, told apart by what its columns mean.
Annotator = Judge = Comparator = Translator = Generator = Segmenter = Detector = Embedder = Reranker = LearnedMetric = Model
