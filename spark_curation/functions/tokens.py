"""Token counts: words in the JVM, or byte-pair tokens of a given vocabulary file in Arrow batches."""

from __future__ import annotations

import base64

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from spark_curation.functions.text import count_words

#: Fixed value: how a text is cut before pairs are merged.
PATTERN = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def encoder(path: str):
    """The encoder of a file of lines of base64 tokens and their ranks."""
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("given", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})


def count(col: Column, scheme: str = "words", path: str | None = None) -> Column:
    """Tokens of a text: ``words``, or ``bpe`` by the vocabulary at ``path``, which every worker must be able to read. A null text has none."""
    if scheme == "words":
        return count_words(col)
    if scheme != "bpe" or path is None:
        raise ValueError("bpe needs the path of a vocabulary")
    held: list = []

    @F.pandas_udf("long")
    def tokens(texts: pd.Series) -> pd.Series:
        if not held:
            held.append(encoder(path))
        return texts.map(lambda t: len(held[0].encode_ordinary(t)) if t else 0).astype("int64")

    return tokens(col)
