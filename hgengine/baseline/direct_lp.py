"""Label propagation written by hand, without programs: what the program layer is measured against."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.session import cut


def direct_labels(hf: HyperFrame, max_rounds: int = 30, until_stable: bool = True) -> DataFrame:
    """vid, label."""
    inc = hf.incidence.select("vid", "hid").persist()
    labels = cut(hf.vertices.select("vid", F.col("vid").alias("label")))
    for _ in range(max_rounds):
        tops = inc.join(labels, "vid").groupBy("hid").agg(F.max("label").alias("top"))
        heard = inc.join(tops, "hid").groupBy("vid").agg(F.max("top").alias("top"))
        both = cut(labels.join(heard, "vid", "left").select("vid", F.col("label").alias("was"), F.greatest("label", "top").alias("label")))
        labels = both.select("vid", "label")
        if until_stable and not both.where("label <> was").limit(1).count():
            break
    return labels
