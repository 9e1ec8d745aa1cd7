"""N-gram language models as tables: fit, probabilities, scores, perplexity. Several models share one pass by lm_id."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BEGIN, END = "<s>", "</s>"
#: Fixed interpolation weights, from the longest context to the uniform floor.
FIXED = {3: (0.5, 0.3, 0.15, 0.05), 2: (0.6, 0.3, 0.1)}


def padded(tokens: Column, n: int) -> Column:
    return F.concat(F.array(*[F.lit(BEGIN)] * (n - 1)), tokens, F.array(F.lit(END))) if n > 1 else F.concat(tokens, F.array(F.lit(END)))


def explode_ngrams(df: DataFrame, tokens: str, n: int, keep: tuple[str, ...] = ()) -> DataFrame:
    """(keep, i, ctx, tok): every token, end mark included, with the n - 1 before it, joined by a blank."""
    p = F.col("__p")
    grams = F.transform(F.sequence(F.lit(n - 1), F.size(p) - 1), lambda i: F.struct((i - (n - 1)).cast("int").alias("i"), F.array_join(F.slice(p, i - (n - 1) + 1, F.lit(n - 1)), " ").alias("ctx"), F.element_at(p, i + 1).alias("tok")))
    return df.withColumn("__p", padded(F.col(tokens), n)).select(*keep, F.explode(grams).alias("g")).select(*keep, "g.i", "g.ctx", "g.tok")


def fit_counts(df: DataFrame, tokens: str, n: int, by: tuple[str, ...] = (), min_count: int = 1) -> DataFrame:
    """(by, n, ctx, tok, cnt) for all orders up to n. One shuffle with partial sums; counts of new data can simply be added."""
    out = None
    for k in range(1, n + 1):
        # the tail of a context of n - 1 is the context of a lower order
        part = explode_ngrams(df, tokens, k, by).select(*by, F.lit(k).alias("n"), "ctx", "tok")
        out = part if out is None else out.unionByName(part)
    counted = out.groupBy(*by, "n", "ctx", "tok").agg(F.count("*").alias("cnt"))
    return counted.filter((F.col("n") < n) | (F.col("cnt") >= min_count)) if min_count > 1 else counted


def merge_counts(a: DataFrame, b: DataFrame) -> DataFrame:
    keys = [c for c in a.columns if c != "cnt"]
    return a.unionByName(b).groupBy(*keys).agg(F.sum("cnt").alias("cnt"))


def with_totals(counts: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """counts with ctx_cnt, the sum of their context: partial sums and joins instead of windows.

    All unigrams have one context, so their total is broadcast, a row a model;
    a frequent context of the higher orders is split by AQE's skew join.
    """
    keys = [*by, "n", "ctx"]
    totals = counts.groupBy(*keys).agg(F.sum("cnt").alias("ctx_cnt"))
    single = counts.filter("n = 1").join(F.broadcast(totals.filter("n = 1")), keys)
    return single.unionByName(counts.filter("n > 1").join(totals.filter("n > 1"), keys))


def probabilities(counts: DataFrame, n: int, smoothing: str = "jm_fixed", by: tuple[str, ...] = (), k: float = 0.1, discount: float = 0.75) -> DataFrame:
    """(by, ctx, tok, p) for every n-gram of the highest order that was seen.

    jm_fixed: fixed interpolation, an unseen context's share is lost (simple SQL; doesn't sum to one).
    jm: the shares of unseen orders are given to the lower ones; as every order of a seen n-gram was
    seen, the two are equal here. addk: additive. kn: absolute
    discount with continuation counts below. What wasn't seen is scored by unseen().
    """
    if smoothing not in ("jm_fixed", "jm", "addk", "kn"):
        raise ValueError(f"no smoothing {smoothing}")
    c = with_totals(counts, by)
    vocab = counts.filter("n = 1").groupBy(*by).agg(F.count("*").alias("v"))
    top = c.filter(F.col("n") == n).select(*by, "ctx", "tok", "cnt", "ctx_cnt")
    top = top.join(F.broadcast(vocab), list(by)) if by else top.crossJoin(F.broadcast(vocab))  # one row a model
    if smoothing == "addk":
        return top.select(*by, "ctx", "tok", ((F.col("cnt") + k) / (F.col("ctx_cnt") + k * F.col("v"))).alias("p"))
    if smoothing == "kn":
        return _kneser_ney(counts, n, by, discount)
    weights = FIXED[n]
    p = weights[0] * F.col("cnt") / F.col("ctx_cnt") + F.lit(weights[-1]) / F.col("v")
    for order in range(n - 1, 0, -1):
        low = c.filter(F.col("n") == order).select(*by, F.col("ctx").alias("__c"), F.col("tok").alias("__t"), (F.col("cnt") / F.col("ctx_cnt")).alias("__p"))
        low = low.withColumnsRenamed({b: f"__{b}" for b in by})
        tail = F.lit("") if order == 1 else F.array_join(F.slice(F.split("ctx", " "), F.lit(n - order + 1), F.lit(order - 1)), " ")
        on = (tail == low["__c"]) & (F.col("tok") == low["__t"])
        for b in by:
            on = on & (F.col(b) == low[f"__{b}"])
        top = top.join(low, on, "left").withColumn(f"p{order}", F.coalesce("__p", F.lit(0.0))).drop("__c", "__t", "__p", *(f"__{b}" for b in by))
        p = p + weights[n - order] * F.col(f"p{order}")
    return top.select(*by, "ctx", "tok", p.alias("p"))


def _kneser_ney(counts: DataFrame, n: int, by: tuple[str, ...], d: float) -> DataFrame:
    """Interpolated: the highest order by counts, the orders below by the number of distinct contexts of a token."""
    cont = counts.filter(F.col("n") == 2).groupBy(*by, "tok").agg(F.count("*").alias("kc"))
    of_all = cont.groupBy(*by).agg(F.sum("kc").alias("of_all"))  # one row a model
    low = cont.join(F.broadcast(of_all), list(by) or F.lit(True)).select(*by, "tok", (F.col("kc") / F.col("of_all")).alias("low"))
    out = None
    for order in range(2, n + 1):
        at = Window.partitionBy(*by, "ctx")
        if order == n:
            rows = counts.filter(F.col("n") == n).select(*by, "ctx", "tok", F.col("cnt").alias("x"))
        else:
            tail = F.array_join(F.slice(F.split("ctx", " "), F.lit(2), F.lit(order - 1)), " ")
            rows = counts.filter(F.col("n") == order + 1).groupBy(*by, tail.alias("ctx"), "tok").agg(F.count("*").alias("x"))
        rows = rows.withColumns({"s": F.sum("x").over(at), "t": F.count("*").over(at)})
        if order == 2:
            rows = rows.join(low, [*by, "tok"])
        else:
            tail = F.array_join(F.slice(F.split("ctx", " "), F.lit(2), F.lit(order - 2)), " ")
            prev = out.select(*by, F.col("ctx").alias("__c"), F.col("tok"), F.col("p").alias("low"))
            rows = rows.withColumn("__c", tail).join(prev, [*by, "__c", "tok"], "left").withColumn("low", F.coalesce("low", F.lit(0.0)))
        out = rows.select(*by, "ctx", "tok", (F.greatest(F.col("x") - d, F.lit(0.0)) / F.col("s") + d * F.col("t") / F.col("s") * F.col("low")).alias("p"))
    return out


def floor_probability(counts: DataFrame, n: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, floor): what an n-gram that wasn't seen gets under the fixed interpolation, the uniform part."""
    return counts.filter("n = 1").groupBy(*by).agg((F.lit(FIXED[n][-1]) / F.count("*")).alias("floor"))


def scores(df: DataFrame, id_col: str, tokens: str, counts: DataFrame, n: int, name: str = "score", by: tuple[str, ...] = ()) -> DataFrame:
    """(id, name): mean ln P over tokens, the end mark included, under fixed interpolation with each order looked up by itself.

    Unseen contexts back off by themselves, as each order is looked up alone. With by, a row meets the model of its by columns.
    """
    weights, by = FIXED[n], list(by)
    grams = explode_ngrams(df, tokens, n, (id_col, *by))
    c = with_totals(counts, tuple(by)).withColumn("q", F.col("cnt") / F.col("ctx_cnt"))
    vocab = counts.filter("n = 1").groupBy(*by).agg(F.count("*").alias("v"))
    # every distinct n-gram is looked up once in each order; the corpus then meets one table
    kinds, p = grams.select(*by, "ctx", "tok").distinct().join(F.broadcast(vocab), by or F.lit(True)), F.lit(weights[-1]) / F.col("v")  # one row a model
    for order in range(n, 0, -1):
        low = c.filter(F.col("n") == order).select(*by, F.col("ctx").alias("__k"), "tok", F.col("q").alias(f"q{order}"))
        tail = F.lit("") if order == 1 else F.array_join(F.slice(F.split("ctx", " "), F.lit(n - order + 1), F.lit(order - 1)), " ")
        kinds = kinds.withColumn("__k", tail).join(low, [*by, "__k", "tok"], "left").drop("__k")
        p = p + weights[n - order] * F.coalesce(F.col(f"q{order}"), F.lit(0.0))
    table = kinds.select(*by, "ctx", "tok", F.log(p).alias("__lp"))
    return grams.join(table, [*by, "ctx", "tok"]).groupBy(id_col).agg(F.avg("__lp").alias(name))


def perplexity(df: DataFrame, id_col: str, tokens: str, counts: DataFrame, n: int) -> DataFrame:
    """One row: exp of the token-weighted mean of -ln P."""
    size = df.select(id_col, (F.size(tokens) + 1).alias("__n"))
    s = scores(df, id_col, tokens, counts, n).join(size, id_col)
    return s.agg(F.exp(-F.sum(F.col("score") * F.col("__n")) / F.sum("__n")).alias("perplexity"))
