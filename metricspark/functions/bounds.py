"""Pruning and validation by the triangle inequality, as Column predicates. Ties survive pruning: it needs strict excess."""
from __future__ import annotations

from pyspark.sql import Column, functions as F


def object_prunable(d_oc: Column, d_qc: Column, r: Column) -> Column:
    """The stored distance to a centre and the query's differ by more than r."""
    return ~d_oc.between(d_qc - r, d_qc + r)


def object_valid(d_oc: Column, d_qc: Column, r: Column) -> Column:
    """The way over the centre is within r already."""
    return d_oc + d_qc <= r


def cluster_prunable(d_qc: Column, radius: Column, r: Column) -> Column:
    return d_qc > r + radius


def cluster_valid(d_qc: Column, radius: Column, r: Column) -> Column:
    return d_qc <= r - radius


def parent_prunable(dist_to_parent: Column, d_qparent: Column, radius: Column, r: Column) -> Column:
    """No distance to the child's centre is needed to drop it."""
    return F.abs(dist_to_parent - d_qparent) > r + radius


def upper(d_qc: Column, radius: Column) -> Column:
    return d_qc + radius


def lower(d_qc: Column, radius: Column) -> Column:
    return F.greatest(d_qc - radius, F.lit(0.0))


def knn_prunable(d_qc: Column, radius: Column, bound: Column) -> Column:
    return d_qc > bound + radius
