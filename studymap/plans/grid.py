"""The ablation grid: every layer once for all studies, then each variant as an order over one wide table."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.lineage import cut
from ..functions.portable import MICRO
from ..operators import layers, votes
from .cascade import Config, Corpus, meta_ballot, net_ballot

ORDERS = {
    "no_network": ("l1", "l2", "l3", "l4"), "network_l1": ("l5", "l1", "l2", "l3", "l4"), "network_l2": ("l1", "l5", "l2", "l3", "l4"), "network_l3": ("l1", "l2", "l5", "l3", "l4"),
    "network_l4": ("l1", "l2", "l3", "l5", "l4"), "network_l5": ("l1", "l2", "l3", "l4", "l5"), "hybrid_h1": ("l1", "l2", "l3", "h1"), "hybrid_h2": ("h2",),
    "hybrid_h1_minvr": ("l1", "l2", "l3", "h1_min"), "network_l5_minvr": ("l1", "l2", "l3", "l4_min", "l5"), "network_only": ("l5",),
}
PLACE = {"l1": 1, "l2": 2, "l3": 3, "l4": 4, "l4_min": 4, "l5": 5, "h1": 6, "h1_min": 6, "h2": 6}


def layer_table(c: Corpus, cfg: Config = Config()) -> DataFrame:
    """(study_id, l1, l2, l3, l4, l4_min, l5, h1, h1_min, h2): each layer's label or null."""
    slim = replace(cfg, tier="min")
    header = {"l1": layers.match_code(c.study, c.code_ref), "l2": layers.match_description(c.study, c.desc_ref), "l3": layers.match_partial(c.study, c.keyword_ref)}
    header = {k: cut(v.select("study_id", "label")) for k, v in header.items()}
    meta, meta_min, net = cut(votes.ballot(meta_ballot(c, None, cfg))), cut(votes.ballot(meta_ballot(c, None, slim))), cut(votes.ballot(net_ballot(c, None, cfg)))
    heads = None
    for v in header.values():
        one = v.withColumn("weight_u", F.lit(MICRO).cast("long"))
        heads = one if heads is None else heads.unionByName(one)
    ballots = {"l4": meta, "l4_min": meta_min, "l5": net, "h1": meta.unionByName(net), "h1_min": meta_min.unionByName(net), "h2": heads.unionByName(meta).unionByName(net)}
    every = None
    for name, x in (header | {k: votes.decide(b, cfg.majority) for k, b in ballots.items()}).items():
        one = x.select("study_id", F.lit(name).alias("_name"), "label")
        every = one if every is None else every.unionByName(one)
    wide = every.groupBy("study_id").agg(*(F.max(F.when(F.col("_name") == n, F.col("label"))).alias(n) for n in PLACE))
    return cut(c.study.select("study_id").join(wide, "study_id", "left"))


def outcomes(wide: DataFrame, variant: str) -> DataFrame:
    """(study_id, label, layer) of a variant's answered studies."""
    order = ORDERS[variant]
    layer = F.coalesce(*(F.when(F.col(n).isNotNull(), F.lit(PLACE[n])) for n in order))
    return wide.select("study_id", F.coalesce(*order).alias("label"), layer.alias("layer")).where("label is not null")


def all_outcomes(wide: DataFrame, beside: dict | None = None) -> DataFrame:
    """The wide table's rows once for each variant, with `variant`, `label` and `layer` (null where unanswered). `beside`: further variants, name -> (label column, layer)."""
    cells = []
    for name, order in ORDERS.items():
        layer = F.coalesce(*(F.when(F.col(n).isNotNull(), F.lit(PLACE[n])) for n in order))
        cells.append(F.struct(F.lit(name).alias("variant"), F.coalesce(*order).alias("label"), layer.alias("layer")))
    for name, (column, place) in (beside or {}).items():
        cells.append(F.struct(F.lit(name).alias("variant"), F.col(column).alias("label"), F.when(F.col(column).isNotNull(), F.lit(place)).alias("layer")))
    return wide.withColumn("_v", F.explode(F.array(*cells))).select(*wide.columns, "_v.variant", "_v.label", "_v.layer")
