"""A hook for scorers from elsewhere (neural sequence models, remote services): anything that gives a score for each label takes the place of the engine, and decisions, guards and measures
work on what it adds."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import decide
from .io import spread
from .schemas import TOP
from .score import _TOP_ARROW, ADDED, _log_prior, _top


@dataclass
class Scorer:
    """load runs once in each worker and returns a function from texts to log scores [texts, labels]; it must be picklable."""

    labels: list[str]
    load: Callable[[], Callable[[list[str]], np.ndarray]]
    batch: int = 256

    def score_udf(self):
        """A vectorised function text -> array of scores in the order of the labels; null for a null or empty text."""
        load, batch = self.load, self.batch

        @F.pandas_udf("array<double>")
        def score(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
            f = load()
            for s in parts:
                out: list = [None] * len(s)
                own = [k for k, t in enumerate(s) if t]
                for at in range(0, len(own), batch):
                    some = own[at : at + batch]
                    for k, row in zip(some, f([s.iloc[k] for k in some]), strict=True):
                        out[k] = [float(x) for x in row]
                yield pd.Series(out)

        return score

    def transform(self, df: DataFrame, text_col: str = "text", topk: int = 5, prior: dict[str, float] | None = None) -> DataFrame:
        """Adds what SegmentModel.transform adds."""
        order = np.argsort(np.array(self.labels), kind="stable")
        names = np.array(self.labels, dtype=object)[order]
        add = _log_prior(list(names), prior)
        work = spread(df.drop(*ADDED)).select(F.struct("*").alias("row"), self.score_udf()(F.col(f"`{text_col}`")).alias("s"))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                rows = b.column("s").to_pylist()
                has = np.array([r is not None for r in rows], bool)
                tops, z = [None] * len(rows), np.zeros(len(rows))
                if has.any():
                    found, total = _top(np.array([r for r in rows if r is not None])[:, order] + add, names, topk)
                    z[has] = total
                    for k, t in zip(np.flatnonzero(has), found, strict=True):
                        tops[k] = t
                yield pa.RecordBatch.from_arrays([b.column("row"), pa.array(tops, _TOP_ARROW), pa.array(z, pa.float64(), mask=~has)], names=["row", *ADDED])

        out = work.mapInArrow(run, T.StructType([work.schema["row"], T.StructField("topk", T._parse_datatype_string(TOP)), T.StructField("log_total", T.DoubleType())]))
        return decide.decorate(out.select("row.*", *ADDED))
