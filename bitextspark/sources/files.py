"""File sources and sinks of pairs and n-best lists."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

PAIR = "pair_id string, src string, tgt string, src_lang string, tgt_lang string, genre string, origin string"


def read_aligned(spark: SparkSession, src_path: str, tgt_path: str) -> DataFrame:
    """(line, src, tgt) of two line-aligned files, by line number.

    Text files are read in splits without line numbers, so each split's lines
    are counted first (one number a split on the driver) and numbered from the
    sum of the splits before it. Split order within a file is its partition
    order as long as each file is one path.
    """

    def numbered(path: str, name: str) -> DataFrame:
        # a file's splits come in order of their offset when they are not packed by size
        lines = spark.read.text(path).select(F.col("_metadata.file_block_start").alias("b"), F.monotonically_increasing_id().alias("m"), F.col("value").alias(name))
        sizes = lines.groupBy("b").agg(F.count("*").alias("n"), F.min("m").alias("m0")).collect()  # a row a split
        start, rows = 0, []
        for r in sorted(sizes, key=lambda r: r["b"]):
            rows.append((r["b"], r["m0"], start))
            start += r["n"]
        offsets = F.broadcast(spark.createDataFrame(rows, "b long, m0 long, start long"))
        return lines.join(offsets, "b").select((F.col("m") - F.col("m0") + F.col("start")).alias("line"), name)

    return numbered(src_path, "src").join(numbered(tgt_path, "tgt"), "line", "full_outer")


def read_tsv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("src string, tgt string").option("sep", "\t").option("quote", "").csv(path)


def read_nbest(spark: SparkSession, path: str) -> DataFrame:
    """JSON lines: sent_id, hyp_rank, hyp, nmt, feats."""
    return spark.read.schema("sent_id string, hyp_rank int, hyp string, nmt double, feats map<string,double>").json(path)


def write_pairs(pairs: DataFrame, path: str, by: tuple[str, ...] = ("origin", "genre"), mode: str = "overwrite") -> None:
    """Parquet in folders by origin and genre; rows of a folder meet before, so there are few files."""
    pairs.repartition(*by).write.mode(mode).partitionBy(*by).parquet(path)


def write_ngrams(counts: DataFrame, name: str, buckets: int = 64) -> None:
    """A bucketed table, so later joins on the context need no shuffle."""
    counts.write.mode("overwrite").bucketBy(buckets, "ctx").sortBy("ctx").saveAsTable(name)


def write_report(report: DataFrame, path: str) -> None:
    report.write.mode("overwrite").json(path)
