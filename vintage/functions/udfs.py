"""Python extension points; each has a native counterpart that plans use instead."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def score_with(probes: DataFrame, make: Callable[[], Callable[[list[list[str]]], list[list[float]]]], toks: str = "toks") -> DataFrame:
    """Scores of any outside model: (probe's columns without tokens, ppl, n_tokens).

    ``make`` is called once a worker task and returns a function from token lists
    to per-token log-probabilities, so a model is loaded once and fed in batches.
    """
    keys = [f for f in probes.schema.fields if f.name != toks]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model = make()
        for b in batches:
            lps = model([list(x) for x in b[toks]])
            out = b[[k.name for k in keys]].copy()
            out["ppl"] = [float(pow(2.718281828459045, -sum(x) / len(x))) if x else None for x in lps]
            out["n_tokens"] = [len(x) for x in lps]
            yield out

    return probes.mapInPandas(run, ", ".join([*(f"`{k.name}` {k.dataType.simpleString()}" for k in keys), "ppl double", "n_tokens int"]))


def from_logprobs(logprobs: DataFrame, keys: list[str], first: int | None = None) -> DataFrame:
    """Perplexities of imported per-token scores (keys..., pos, logprob), over the first tokens only if asked."""
    used = logprobs if first is None else logprobs.where(F.col("pos") < first)
    return used.groupBy(*keys).agg(F.exp(-F.avg("logprob")).alias("ppl"), F.count(F.lit(1)).alias("n_tokens"))


def trimmed_mean_udaf(trim: float = 0.025):
    """The trimmed mean as a grouped pandas aggregate."""
    @F.pandas_udf("double")
    def trimmed(v: pd.Series) -> float:
        k = int(len(v) * trim)
        return float(v.sort_values().iloc[k : len(v) - k].mean())

    return trimmed


def cutoff_with(curve: DataFrame, rule: Callable[[pd.DataFrame], int]) -> DataFrame:
    """(model, cutoff) by a rule of the user's on each model's curve; a curve has one row a month."""
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"model": [pdf["model"].iloc[0]], "cutoff": [int(rule(pdf.sort_values("month_ix")))]})

    return curve.groupBy("model").applyInPandas(run, "model string, cutoff int")


def ngrams_udtf():
    """A table function ngrams(text, n): one row a run of n words."""
    @F.udtf(returnType="pos: int, gram: string")
    class Ngrams:
        def eval(self, text: str, n: int):
            w = (text or "").split(" ")
            for i in range(len(w) - n + 1):
                yield i, " ".join(w[i : i + n])

    return Ngrams
