"""All parameters of staged labeling in one place."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Settings:
    easy_ratio: float = 0.30  # share of all pairs that get easy labels
    easy_lo: float = 0.3
    easy_hi: float = 0.8
    m: int | None = 2000  # candidates by support; None: all
    k: int = 10  # candidates by certainty
    interval_cap: int = 200  # evidence per feature and interval
    bins: int = 10
    error_bound: float = 1.0  # log-odds; the reference gives no value
    label_eps: float = 0.01  # a label's log-odds are ln((1 - eps) / eps)
    tau_max: float = 20.0
    confidence_scale: str = "normalized"  # or "raw"
    sigma_power: int = 1  # 2: the printed form of the bound
    class_weight: bool = True
    support_mode: str = "combine"  # or "mean_logit", which does not favour many features
    clip: bool = False  # clip the closed-form curve into the box of the fit
    idf_min: float = 3.0
    df_min: int = 2
    threshold: float = 0.5
    labels_per_round: int = 1  # more is ours, for scale
    h_max: float | None = None  # of further labels in one round
    max_rounds: int | None = None
    use_mle: bool = True
    fit_above: float = 0.0  # ours: fit only candidates whose approximate entropy is over this; 0: all, as the method asks
    refresh: float = 0.0  # ours: a feature is refreshed when its evidence has grown by this share; 0: in every round
    unsupported: str = "match"  # pairs without an active feature: match, nonmatch or similarity
    seed: int = 42

    @property
    def label_logit(self) -> float:
        from math import log

        return log((1 - self.label_eps) / self.label_eps)
