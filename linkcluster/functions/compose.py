"""Pair measures: one object scores links, intra-cluster pairs and representatives alike."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkcluster.functions import geo, strings


def mean_of(*sims: Column) -> Column:
    """Unweighted mean over the similarities that are present; null when none is."""
    return weighted([(1.0, s) for s in sims], empty=None)


def weighted(parts: list[tuple[float, Column]], missing: str = "renormalize", empty: float | None = 0.0) -> Column:
    """Weighted combination; a property absent on either side has a null similarity.

    ``renormalize`` leaves out absent properties and their weights, ``zero`` counts them as 0.
    """
    total = sum((F.coalesce(s * w, F.lit(0.0)) for w, s in parts), F.lit(0.0))
    if missing == "zero":
        return total / sum(w for w, _ in parts)
    weight = sum((F.when(s.isNotNull(), F.lit(float(w))).otherwise(F.lit(0.0)) for w, s in parts), F.lit(0.0))
    return F.when(weight > 0, total / weight).otherwise(F.lit(empty).cast("double"))


@dataclass(frozen=True)
class PairMeasure:
    """``columns`` of an entity and ``score`` of a pair whose sides are named l_<col> and r_<col>."""

    name: str
    columns: tuple[str, ...]
    score: Callable[[Callable[[str], Column], Callable[[str], Column]], Column]
    #: (column, weight) of a measure that is the ``weighted`` mean of Jaro-Winkler similarities, absent ones left out.
    weights: tuple[tuple[str, float], ...] = ()

    def side(self, entities: DataFrame, prefix: str, *keep: str) -> DataFrame:
        """The narrow side of a pair join: id, kept columns and what the measure reads."""
        return entities.select(*[F.col(c).alias(f"{prefix}{c}") for c in dict.fromkeys(("id", *keep, *self.columns))])

    def apply(self, pairs: DataFrame, name: str = "sim") -> DataFrame:
        s = self.score(lambda c: F.col(f"l_{c}"), lambda c: F.col(f"r_{c}"))
        return pairs.withColumn(name, F.floor(F.coalesce(s, F.lit(0.0)) * 1e9 + 0.5) / 1e9)


LABEL = PairMeasure("label", ("label",), lambda a, b: strings.jaro_winkler(a("label"), b("label")))
LABEL_LEVENSHTEIN = PairMeasure("levenshtein", ("label",), lambda a, b: strings.levenshtein_ratio(a("label"), b("label")))
LABEL_GEO = PairMeasure(
    "label_geo", ("label", "lat", "lon"), lambda a, b: weighted([(0.5, strings.jaro_winkler(a("label"), b("label"))), (0.5, F.when(a("lat").isNotNull() & b("lat").isNotNull(), F.coalesce(geo.geo_similarity(a("lat"), a("lon"), b("lat"), b("lon")), F.lit(0.0))))])
)
_MUSIC = (("title", 0.6), ("artist", 0.3), ("album", 0.1))
MUSIC = PairMeasure("music", ("title", "artist", "album"), lambda a, b: weighted([(w, strings.jaro_winkler(a(c), b(c))) for c, w in _MUSIC]), _MUSIC)
