"""SQL functions of a model: detect_label, label_margin, label_topk, label_posterior, segment_text, the table functions label_scores and chunks, and the
aggregate label_mixture."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from . import em, lattice
from .model import SegmentModel, block_matrix
from .schemas import TOP
from .score import Kernel


class Scorer:
    """Scores single texts in a worker; the pattern is that of the built-in pre-tokeniser."""

    def __init__(self, parts: tuple, labels: list[str], kind: str, prefix_space: bool, unit: str) -> None:
        import regex

        self.kernel, self.labels, self.kind, self.prefix_space, self.unit = Kernel(*parts, "best"), labels, kind, prefix_space, unit
        # built-in patterns know ASCII white space only
        self.pattern = regex.compile(r" ?\p{L}+| ?[^ \t\n\x0b\f\r\p{L}]+|[ \t\n\x0b\f\r]+" if kind == "regex" else r" ?[^ \t\n\x0b\f\r]+|[ \t\n\x0b\f\r]+")

    def chunks(self, text: str) -> list[str]:
        if self.prefix_space and text and not text.startswith(" "):
            text = f" {text}"
        found = [text] if self.kind == "none" else self.pattern.findall(text)
        return [c.encode().decode("latin-1") for c in found] if self.unit == "byte" else found

    def scores(self, text: str | None) -> np.ndarray | None:
        if not text:
            return None
        return self.kernel.scores(self.chunks(text)).sum(axis=0) / em.SCALE

    def ranked(self, text: str | None) -> list[tuple[str, float]] | None:
        s = self.scores(text)
        return None if s is None else sorted(zip(self.labels, s.tolist(), strict=True), key=lambda x: (-x[1], x[0]))


def register(spark: SparkSession, model: SegmentModel) -> None:
    """Registers the functions for a session. Nulls and empty texts give nulls."""
    labels = model.labels()
    sent, how = spark.sparkContext.broadcast(block_matrix(model, labels, "best")), (model.kind, model.prefix_space, model.unit)
    held: dict[str, Scorer] = {}

    def scorer() -> Scorer:
        if "s" not in held:
            held["s"] = Scorer(sent.value, labels, *how)
        return held["s"]

    @F.pandas_udf("string")
    def detect_label(text: pd.Series) -> pd.Series:
        s = scorer()
        return pd.Series([r[0][0] if (r := s.ranked(t)) else None for t in text])

    @F.pandas_udf("double")
    def label_margin(text: pd.Series) -> pd.Series:
        s = scorer()
        return pd.Series([r[0][1] - r[1][1] if (r := s.ranked(t)) and len(r) > 1 else None for t in text], dtype="float64")

    @F.pandas_udf(TOP)
    def label_topk(text: pd.Series, k: pd.Series) -> pd.Series:
        s = scorer()
        return pd.Series([[{"label": a, "score": b} for a, b in r[: int(n)]] if (r := s.ranked(t)) else None for t, n in zip(text, k, strict=True)])

    @F.pandas_udf("map<string,double>")
    def label_posterior(text: pd.Series) -> pd.Series:
        s = scorer()

        def one(t: str | None) -> dict | None:
            r = s.ranked(t)
            if not r:
                return None
            p = {a: math.exp(b - r[0][1]) for a, b in r}
            z = sum(p.values())
            return {a: x / z for a, x in p.items()}

        return pd.Series([one(t) for t in text])

    @F.pandas_udf("array<string>")
    def segment_text(text: pd.Series, label: pd.Series) -> pd.Series:
        s = scorer()
        ids, matrix = s.kernel.ids, s.kernel.matrix
        one = lambda t, x: None if not t or x not in labels else [k for c in s.chunks(t) for k in lattice.segment_one(c, ids, s.kernel.longest, matrix[:, labels.index(x)])[0]]
        return pd.Series([one(t, x) for t, x in zip(text, label, strict=True)])

    @F.pandas_udf("map<string,double>")
    def label_mixture(text: pd.Series) -> dict:
        """Posterior of one label for all texts of a group together."""
        s = scorer()
        total = sum((x for t in text if (x := s.scores(t)) is not None), np.zeros(len(labels)))
        p = np.exp(total - total.max())
        return dict(zip(labels, (p / p.sum()).tolist(), strict=True))

    for name, f in (("detect_label", detect_label), ("label_margin", label_margin), ("label_topk", label_topk), ("label_posterior", label_posterior), ("segment_text", segment_text), ("label_mixture", label_mixture)):
        spark.udf.register(name, f)

    @F.udtf(returnType="label string, score double, rank int")
    class LabelScores:
        def __init__(self) -> None:
            self.s = Scorer(sent.value, labels, *how)

        def eval(self, text: str) -> Iterator[tuple]:
            for k, (a, b) in enumerate(self.s.ranked(text) or []):
                yield a, b, k + 1

    @F.udtf(returnType="chunk string, place int")
    class Chunks:
        def __init__(self) -> None:
            self.s = Scorer(sent.value, labels, *how)

        def eval(self, text: str) -> Iterator[tuple]:
            for k, c in enumerate(self.s.chunks(text or "")):
                yield c, k

    @F.udtf(returnType="tokens array<string>")
    class Segmentations:
        """All splits of a short text."""

        def __init__(self) -> None:
            self.ids = sent.value[0]

        def eval(self, text: str) -> Iterator[tuple]:
            def walk(at: int, said: list[str]) -> Iterator[tuple]:
                if at == len(text):
                    yield (said,)
                for e in range(at + 1, len(text) + 1):
                    if text[at:e] in self.ids:
                        yield from walk(e, [*said, text[at:e]])

            if text and len(text) <= 12:
                yield from walk(0, [])

    spark.udtf.register("label_scores", LabelScores)
    spark.udtf.register("chunks", Chunks)
    spark.udtf.register("segmentations", Segmentations)
