"""Word noise for back-translation, row by row and without a shuffle: delete, blank, swap."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .hashing import uniform

FILLER = "<blank>"


def bound(tokens: Column, key: Column, work) -> Column:
    """work(tokens, key) with both as names, by a transform of one element: expressions of them would be worked out again for each token."""
    held = F.struct(tokens.alias("t"), key.alias("k"))
    return F.get(F.transform(F.array(held), lambda x: work(x["t"], x["k"])), F.lit(0))


def noise_delete(tokens: Column, key: Column, p: float = 0.05, seed: str = "del") -> Column:
    """Each token goes with probability p."""
    return bound(tokens, key, lambda toks, k: F.filter(toks, lambda t, i: uniform(k, i, seed) >= p))


def noise_blank(tokens: Column, key: Column, p: float = 0.05, filler: str = FILLER, seed: str = "blank") -> Column:
    """Each token becomes the filler with probability p."""
    return bound(tokens, key, lambda toks, k: F.transform(toks, lambda t, i: F.when(uniform(k, i, seed) < p, F.lit(filler)).otherwise(t)))


def noise_swap(tokens: Column, key: Column, p: float = 0.05, style: str = "adjacent", window: int = 3, seed: str = "swap") -> Column:
    """adjacent: positions 2j and 2j+1 change places with probability p. local: a permutation that moves no token by more than window."""
    return bound(tokens, key, lambda toks, k: _swapped(toks, k, p, style, window, seed))


def _swapped(tokens: Column, key: Column, p: float, style: str, window: int, seed: str) -> Column:
    if style == "local":
        moved = F.transform(tokens, lambda t, i: F.struct((i + (window + 1) * uniform(key, i, seed)).alias("k"), i.alias("i"), t.alias("t")))
        return F.transform(F.array_sort(moved), lambda x: x["t"])

    def at(_: Column, i: Column) -> Column:
        j = F.floor(i / 2)
        other = F.when(i % 2 == 0, i + 1).otherwise(i - 1)
        swap = (uniform(key, j, seed) < p) & (other < F.size(tokens))
        return F.get(tokens, F.when(swap, other).otherwise(i).cast("int"))

    return F.transform(tokens, at)


def add_noise(tokens: Column, key: Column, p: float = 0.05) -> Column:
    return noise_swap(noise_blank(noise_delete(tokens, key, p), key, p), key, p)
