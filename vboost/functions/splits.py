"""Split gains and leaf weights for scalar and vector leaves."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def node_score(g: Column, h: Column, reg_lambda: float) -> Column:
    return g * g / (h + reg_lambda)


def gain(gl: Column, hl: Column, g: Column, h: Column, reg_lambda: float) -> Column:
    """Half of what the children's scores add to the parent's."""
    return 0.5 * (node_score(gl, hl, reg_lambda) + node_score(g - gl, h - hl, reg_lambda) - node_score(g, h, reg_lambda))


def leaf_weight(g: Column, h: Column, reg_lambda: float) -> Column:
    return -g / (h + reg_lambda)


def leaf_weight_mo(g: Column, h: Column, reg_lambda: float) -> Column:
    return F.zip_with(g, h, lambda a, b: -a / (b + reg_lambda))


def node_score_mo(g: Column, h: Column, reg_lambda: float) -> Column:
    """Sum over classes of the square of the class's own gradient sum: one class gives the scalar score."""
    return F.aggregate(F.zip_with(g, h, lambda a, b: a * a / (b + reg_lambda)), F.lit(0.0), lambda s, x: s + x)


def gain_mo(gl: Column, hl: Column, g: Column, h: Column, reg_lambda: float) -> Column:
    minus = lambda a, b: F.zip_with(a, b, lambda x, y: x - y)
    return 0.5 * (node_score_mo(gl, hl, reg_lambda) + node_score_mo(minus(g, gl), minus(h, hl), reg_lambda) - node_score_mo(g, h, reg_lambda))
