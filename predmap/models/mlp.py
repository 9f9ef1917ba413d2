"""Multi-layer perceptron with ReLU."""

from __future__ import annotations

from dataclasses import dataclass

from predmap.models.core import Trained


@dataclass
class MLP(Trained):
    hidden: int = 1
    units: int = 50
    kind = "mlp"

    def shapes(self, features, classes):
        return [features, *[self.units] * self.hidden, classes]
