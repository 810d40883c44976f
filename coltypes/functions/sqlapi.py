"""SQL entry: views of a prepared collection and functions under SQL names."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from coltypes.functions.encoders import NgramEncoder, encoder_udf
from coltypes.operators import models, tokens


def functions() -> dict:
    """The functions by SQL name; made when asked for, since return types are parsed by a session."""

    @F.pandas_udf("double")
    def cosine_of(a: pd.Series, b: pd.Series) -> pd.Series:
        """Cosine of two arrays, in Arrow batches."""
        import numpy as np

        def one(x, y) -> float:
            n = float(np.linalg.norm(x) * np.linalg.norm(y))
            return float(np.dot(x, y)) / n if n else 0.0

        return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)])

    @F.pandas_udf("array<double>")
    def vector_mean(v: pd.Series) -> list[float]:
        """Element-wise mean of vectors, as a grouped aggregate."""
        import numpy as np

        return np.mean(np.stack(v.to_list()), axis=0).tolist()

    @F.pandas_udf("long")
    def estimated_tokens(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for t in texts:
            yield t.fillna("").map(tokens.estimate)

    @udtf(returnType="value string, len int")
    class LengthSample:
        """length_sample(values, k): at most k values spread over string lengths, for one array; the frame form scales."""

        def eval(self, values: list[str], k: int):
            from hashlib import md5

            strata: dict[int, list[str]] = {}
            for v in sorted(set(values or []), key=lambda x: (md5(f"{x}#0".encode()).hexdigest(), x)):
                strata.setdefault(len(v), []).append(v)
            order = sorted(strata, key=lambda n: (-len(strata[n]), n))
            turn, left = 0, k
            while left and any(len(strata[n]) > turn for n in order):
                for n in order:
                    if left and len(strata[n]) > turn:
                        yield strata[n][turn], n
                        left -= 1
                turn += 1

    @udtf(returnType="header string, label string")
    class DiscoverTypes:
        """discover_types(header, values, kind): the types that the offline model proposes for one column."""

        def eval(self, header: str, values: list[str], kind: str):
            request = {"headers": [header], "sample": list(values or []), "kind": kind, "candidates": [], "context": []}
            for label in models.RuleModel().propose(request):
                yield header, label

    return {"encode_text": encoder_udf(NgramEncoder()), "cosine_of": cosine_of, "vector_mean": vector_mean, "estimated_tokens": estimated_tokens, "length_sample": LengthSample, "discover_types": DiscoverTypes}


def register(spark: SparkSession, views: dict[str, DataFrame] | None = None) -> None:
    """encode_text, cosine_of, vector_mean, estimated_tokens, length_sample, discover_types, and temp views."""
    for name, f in functions().items():
        (spark.udtf if name in ("length_sample", "discover_types") else spark.udf).register(name, f)
    for name, df in (views or {}).items():
        df.createOrReplaceTempView(name)
