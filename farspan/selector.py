"""The selector as an estimator: fit gives moments, transform gives combined scores, select gives a training set."""

from __future__ import annotations

from pyspark.sql import DataFrame

from farspan.config import Config
from farspan.operators import profiles, score, select, windows


class LongDependencySelector:
    def __init__(self, config: Config | None = None, profile=None):
        self.config = config or Config.paper()
        self.profile = profile or profiles.named(self.config.profile)
        self.moments: DataFrame | None = None

    def windows(self, documents: DataFrame) -> DataFrame:
        """documents (doc_id, category, text, ..) to windows; only a scan of fewer tasks than cores is dealt anew, as text."""
        c = self.config
        long = windows.spread(windows.long_only(documents, c.L, c.token_mode))
        return windows.cut(windows.tokenize(long, c.token_mode), c.L)

    def raw(self, cut: DataFrame) -> DataFrame:
        c = self.config
        return score.score_windows(cut, self.profile, c.k, c.block, c.var_over, c.ddof, c.head_agg)

    def fit(self, raw: DataFrame) -> LongDependencySelector:
        self.moments = score.moments(raw, self.config.std_scope, self.config.ddof)
        return self

    def transform(self, raw: DataFrame) -> DataFrame:
        if self.moments is None:
            raise ValueError("fit first")
        return score.combine(score.standardize(raw, self.config.std_scope, known=self.moments), self.config.alpha)

    def select(self, scored: DataFrame, budget: int, distributed: bool = False) -> DataFrame:
        """``distributed``: by thresholds, without a rank for every window that is taken."""
        chosen = select.top_by_threshold if distributed else select.top_by_budget
        return chosen(scored, budget, self.config.L)
