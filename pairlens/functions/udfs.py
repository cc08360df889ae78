"""Arrow functions over the kernels, for what built-in expressions can't express."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from pairlens.functions import kernels as K


@F.pandas_udf("int")
def lcs_length(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([K.lcs_length(list(x), list(y)) for x, y in zip(a, b, strict=True)])


@F.pandas_udf("int")
def char_lcs_length(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else K.lcs_length(x, y) for x, y in zip(a, b, strict=True)], dtype="Int32")


@F.pandas_udf("int")
def substring_length(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else K.substring_length(x, y) for x, y in zip(a, b, strict=True)], dtype="Int32")


@F.pandas_udf("string")
def stem_de(w: pd.Series) -> pd.Series:
    return w.map(K.stem_de)


@F.pandas_udf("double")
def rouge1_f(pred: pd.Series, target: pd.Series) -> pd.Series:
    return pd.Series([K.rouge_n(K.tokenize(x), K.tokenize(y), 1)[2] for x, y in zip(pred, target, strict=True)], dtype=float)


@F.pandas_udf("double")
def rouge_lsum(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([K.rouge_lsum([K.tokenize(s) for s in x], [K.tokenize(s) for s in y])[2] for x, y in zip(a, b, strict=True)])


@F.pandas_udf("coverage double, density double")
def fragment_stats(a: pd.Series, b: pd.Series) -> pd.DataFrame:
    return pd.DataFrame([K.fragments(list(x), list(y)) for x, y in zip(a, b, strict=True)], columns=["coverage", "density"])


@F.pandas_udf("double")
def loop_length(a: pd.Series) -> pd.Series:
    return pd.Series([K.loop_length(list(x)) for x in a])


@F.pandas_udf("array<string>")
def blocked(a: pd.Series) -> pd.Series:
    return pd.Series([K.block_repeats(list(x)) for x in a])


@F.pandas_udf("double")
def novel_share(gram: pd.Series, known: pd.Series) -> float:
    """Share of a group's distinct grams that aren't known. A group goes to one task: group by pair, not by corpus."""
    mine = set(gram.dropna())
    return len(mine - set(gram[known.astype(bool)])) / len(mine) if mine else 0.0
