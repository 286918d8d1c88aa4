"""Min-hash by seeds, concatenated keys, keyword tokens and secret-keyed ids."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def minhash(items, seed: int, fn: str = "xxhash64") -> Column:
    """Least hash of the set's items under one seed. ``md5`` gives strings that any engine
    reproduces; ``xxhash64`` is the fast form."""
    if fn == "md5":
        return F.array_min(F.transform(items, lambda x: F.md5(F.concat(F.lit(f"{seed}|"), x))))
    if fn != "xxhash64":
        raise ValueError(f"unknown hash {fn}")
    return F.array_min(F.transform(items, lambda x: F.xxhash64(F.lit(seed), x)))


def signature(items, seeds: Sequence[int], fn: str = "xxhash64") -> Column:
    return F.array(*(minhash(items, s, fn) for s in seeds))


def lsh_key(items, p: int, fn: str = "xxhash64", first: int = 0) -> Column:
    """p min-hashes in one string: two sets agree with probability Jaccard to the power p."""
    return F.concat_ws("-", *(minhash(items, first + s, fn).cast("string") for s in range(p)))


def char_multiset(word) -> Column:
    """Characters with their occurrence numbers, so that repeats count and order does not."""
    chars = F.filter(F.split(word, ""), lambda c: c != "")
    return F.transform(chars, lambda c, i: F.concat(c, F.size(F.filter(F.slice(chars, 1, i + 1), lambda d: d == c)).cast("string")))


def keyword_token(word, hashes: int = 2, fn: str = "xxhash64") -> Column:
    """Concatenated min-hashes of a keyword's characters; likely equal for misspellings."""
    return lsh_key(char_multiset(word), hashes, fn, first=1000)


def secret_id(secret: str, *parts) -> Column:
    """A fresh identifier that only the holder of the secret can link; stable under recomputation."""
    return F.sha2(F.concat_ws("\x1f", F.lit(secret), *(F.col(p).cast("string") if isinstance(p, str) else p.cast("string") for p in parts)), 256)
