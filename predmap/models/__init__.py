"""Models that give every key integer weights over the values."""

from predmap.models.core import BucketTable, Constant, Custom, GaussianNB, Logistic, Model, Point, predict_weights  # noqa: F401
from predmap.models.mlp import MLP  # noqa: F401
