"""Variants of the cascade: network at any place, none, alone; both merged-vote hybrids; minimal rules."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.lineage import cut
from ..functions.portable import MICRO
from ..operators import layers, votes
from .cascade import Config, Corpus, classify, meta_ballot, net_ballot


def network_at(c: Corpus, place: int, cfg: Config = Config()) -> DataFrame:
    rest = [1, 2, 3, 4]
    rest.insert(place - 1, 5)
    return classify(c, replace(cfg, order=tuple(rest)))


def no_network(c: Corpus, cfg: Config = Config()) -> DataFrame:
    return classify(c, replace(cfg, order=(1, 2, 3, 4)))


def network_only(c: Corpus, cfg: Config = Config()) -> DataFrame:
    return classify(c, replace(cfg, order=(5,)))


def hybrid_h1(c: Corpus, cfg: Config = Config()) -> DataFrame:
    """Layers 1 to 3 as they are, then one ballot of tag and network votes (layer 6)."""
    merged = lambda s: votes.decide(meta_ballot(c, s, cfg).unionByName(net_ballot(c, s, cfg)), cfg.majority)
    return classify(c, replace(cfg, order=(1, 2, 3, 6), extra={6: merged}))


def hybrid_h2(c: Corpus, cfg: Config = Config(), layer_weight: int = 1) -> DataFrame:
    """All evidence in one ballot: header hits vote with layer_weight units beside tags and networks."""
    header = None
    for n, got in ((1, layers.match_code(c.study, c.code_ref)), (2, layers.match_description(c.study, c.desc_ref)), (3, layers.match_partial(c.study, c.keyword_ref))):
        v = got.select("study_id", "label", F.lit(layer_weight * MICRO).cast("long").alias("weight_u"), F.lit(f"layer:{n}").alias("origin"), F.lit(0).alias("series_no"))
        header = v if header is None else header.unionByName(v)
    every = header.unionByName(meta_ballot(c, None, cfg)).unionByName(net_ballot(c, None, cfg))
    return cut(votes.decide(every, cfg.majority).select("study_id", "label", F.lit(6).alias("layer")))


def all_variants(c: Corpus, cfg: Config = Config()) -> dict:
    """Name -> function; every one is a prediction table."""
    slim = replace(cfg, tier="min")
    return {
        "no_network": lambda: no_network(c, cfg),
        **{f"network_l{p}": (lambda p=p: network_at(c, p, cfg)) for p in range(1, 6)},
        "hybrid_h1": lambda: hybrid_h1(c, cfg),
        "hybrid_h2": lambda: hybrid_h2(c, cfg),
        "hybrid_h1_minvr": lambda: hybrid_h1(c, slim),
        "network_l5_minvr": lambda: network_at(c, 5, slim),
        "network_only": lambda: network_only(c, cfg),
    }
