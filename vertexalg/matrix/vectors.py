"""Two layouts of a sparse vector: sorted pairs, and words of a bitmap with dense values."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class PairVector:
    """(vid, val), sorted inside partitions."""

    def __init__(self, df: DataFrame) -> None:
        self.df = df.select("vid", "val").sortWithinPartitions("vid")

    def count(self) -> int:
        return self.df.count()

    def to_bitmap(self) -> BitmapVector:
        return BitmapVector.of(self.df)

    def keep(self, edges: DataFrame, column: str = "src") -> DataFrame:
        return edges.join(self.df.select(F.col("vid").alias(column)), column, "left_semi")


class BitmapVector:
    """(word_no, bits, vals): bit i of word w stands for id 64 w + i; vals has 64 places, null where the bit is unset."""

    def __init__(self, df: DataFrame) -> None:
        self.df = df

    @classmethod
    def of(cls, pairs: DataFrame) -> BitmapVector:
        rows = pairs.select(F.expr("vid div 64").alias("word_no"), F.pmod("vid", F.lit(64)).cast("int").alias("i"), "val").where("val is not null")
        bit = F.expr("shiftleft(1L, i)")
        words = rows.groupBy("word_no").agg(F.bit_or(bit).alias("bits"), F.map_from_entries(F.collect_list(F.struct("i", "val"))).alias("m"))
        return cls(words.select("word_no", "bits", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.element_at("m", i)).alias("vals")))

    def to_pairs(self) -> PairVector:
        rows = self.df.select("word_no", "bits", F.posexplode("vals").alias("i", "val"))
        return PairVector(rows.where("getbit(bits, i) = 1").select((F.col("word_no") * 64 + F.col("i")).alias("vid"), "val"))

    def count(self) -> int:
        return self.df.agg(F.sum(F.bit_count("bits"))).first()[0] or 0

    def keep(self, edges: DataFrame, column: str = "src", broadcast: bool = False) -> DataFrame:
        """Edges whose column is set; broadcast only where the caller has checked the number of words."""
        words = self.df.select("word_no", "bits")
        marked = edges.withColumn("word_no", F.expr(f"{column} div 64"))
        joined = marked.join(F.broadcast(words) if broadcast else words, "word_no")
        return joined.where(F.expr(f"getbit(bits, cast(pmod({column}, 64) as int)) = 1")).drop("word_no", "bits")

    @staticmethod
    def contains(vid: Column) -> Column:
        """Whether the joined word has vid."""
        return F.getbit("bits", F.pmod(vid, F.lit(64)).cast("int")) == 1


def same(a: PairVector, b: PairVector) -> bool:
    """Equal as sets of pairs."""
    return a.df.exceptAll(b.df).isEmpty() and b.df.exceptAll(a.df).isEmpty()
