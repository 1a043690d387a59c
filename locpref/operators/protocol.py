"""The exchange of messages as three functions, so that what crosses the trust line can be checked."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from .factorization import FitConfig, item_gradient, residuals, step, user_gradient, weighted
from .private import PrivateConfig, aggregate_reports, client_reports


@dataclass
class Round:
    """Publish factors, let clients answer, update; ``private`` decides what the answer is."""

    cfg: FitConfig

    @property
    def private(self) -> bool:
        return isinstance(self.cfg, PrivateConfig)

    def publish(self, X: DataFrame, Z: DataFrame) -> tuple[DataFrame | None, DataFrame]:
        """The item side goes to everyone; user vectors stay at home in the private form."""
        return (None if self.private else X), Z

    def client(self, triples: DataFrame, X: DataFrame, Z: DataFrame, t: int = 1) -> DataFrame:
        if self.private:
            p, scale = self.cfg.mechanism(Z.count())
            return client_reports(X, triples, Z, self.cfg, t, p, scale).drop("user_id")
        return residuals(weighted(triples, self.cfg), X, Z, self.cfg.d)

    def server(self, answers: DataFrame, X: DataFrame, Z: DataFrame, t: int = 1) -> tuple[DataFrame, DataFrame]:
        gamma = self.cfg.step.at(t)
        if self.private:
            p, _ = self.cfg.mechanism(Z.count())
            return X, step(Z, aggregate_reports(answers, self.cfg, p), "item_id", "z", gamma, self.cfg.lam_z, self.cfg)
        gx = user_gradient(answers, self.cfg.d, weight=answers["wu"])
        gz = item_gradient(answers, self.cfg.d, weight=answers["wz"])
        return step(X, gx, "user_id", "x", gamma, self.cfg.lam_x, self.cfg), step(Z, gz, "item_id", "z", gamma, self.cfg.lam_z, self.cfg)
