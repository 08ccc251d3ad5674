"""Support of patterns: minimum image numbers, exact or capped at the threshold, and plain embedding counts. DataFrame
functions only; what is classified are the distinct raw forms."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.pattern.classify import positions
from levelmine.session import materialise

#: Raw forms are broadcast while at most so many; beyond, they are joined by a shuffle.
BROADCAST_FORMS = 100_000


@dataclass
class Forms:
    """A level's distinct raw forms: (labels, bits, form, n, code, place, orbit), n embeddings each, written once."""

    rows: DataFrame
    few: bool

    def joined(self, level: DataFrame) -> DataFrame:
        return formed(level).join(F.broadcast(self.rows) if self.few else self.rows, ["labels", "bits", "form"])

    def counts(self) -> DataFrame:
        """(code, embeddings)."""
        return self.rows.groupBy("code").agg(F.sum("n").cast("long").alias("embeddings"))


def formed(level: DataFrame) -> DataFrame:
    """The level with form, the text of its edge labels, which together with labels and bits is its raw form."""
    return level.withColumn("form", F.to_json("elabels"))


def forms(level: DataFrame) -> Forms:
    raw = level.groupBy("labels", "bits", "elabels").agg(F.count("*").alias("n"))
    rows = materialise(positions(raw), "forms")
    return Forms(rows, rows.limit(BROADCAST_FORMS + 1).count() <= BROADCAST_FORMS)


def images(level: DataFrame, known: Forms | None = None) -> DataFrame:
    """(code, orbit, vertex): a row for each position of each embedding. Positions of one orbit share their images."""
    pair = F.explode(F.arrays_zip(F.col("orbit"), F.col("verts").alias("vertex"))).alias("p")
    return (known or forms(level)).joined(level).select("code", pair).select("code", F.col("p.orbit").alias("orbit"), F.col("p.vertex").alias("vertex"))


def _least(counts: DataFrame) -> DataFrame:
    return counts.groupBy("code").agg(F.min("n").alias("mni"))


def exact(level: DataFrame, known: Forms | None = None) -> DataFrame:
    """(code, mni): distinct first, then counted, so that no set is ever held in one row."""
    return _least(images(level, known).distinct().groupBy("code", "orbit").agg(F.count("*").alias("n")))


#: Of so many slices of a level the first is counted before the others are looked at.
SLICES = 8


def _images_of_some(level: DataFrame, known: Forms, codes: DataFrame | None = None) -> DataFrame:
    """Images of the patterns not in codes."""
    return images(level, known if codes is None else Forms(known.rows.join(codes, "code", "left_anti"), known.few))


def capped(level: DataFrame, threshold: int, known: Forms | None = None) -> DataFrame:
    """(code, mni, capped): counting stops at the threshold. Patterns that reach it within the first slice of the level
    are decided; of the other slices only the embeddings of patterns still open make images."""
    known = known or forms(level)
    key = "eids" if "eids" in level.columns else "verts"
    first = _images_of_some(level.filter(F.pmod(F.xxhash64(key), F.lit(SLICES)) == 0), known).distinct()
    sizes = first.groupBy("code", "orbit").agg(F.count("*").alias("n"))
    orbits = known.rows.select("code", F.size(F.array_distinct("orbit")).alias("orbits")).distinct()
    enough = sizes.filter(F.col("n") >= threshold).groupBy("code").agg(F.count("*").alias("have")).join(orbits, "code")
    decided = materialise(enough.filter("have = orbits").select("code"), "decided")
    rest = _images_of_some(level, known, decided).distinct().groupBy("code", "orbit").agg(F.least(F.count("*"), F.lit(threshold)).alias("n"))
    both = decided.select("code", F.lit(threshold).cast("long").alias("mni")).unionByName(_least(rest).select("code", F.col("mni").cast("long").alias("mni")))
    return both.withColumn("capped", F.col("mni") >= threshold)


def approximate(level: DataFrame, rsd: float = 0.05) -> DataFrame:
    """(code, mni): a screen by sketches, never the answer."""
    return _least(images(level).groupBy("code", "orbit").agg(F.approx_count_distinct("vertex", rsd).alias("n")))


def count(level: DataFrame, known: Forms | None = None) -> DataFrame:
    """(code, mni): the number of embeddings, which is not anti-monotone; for contrast."""
    return (known or forms(level)).counts().withColumnRenamed("embeddings", "mni")
