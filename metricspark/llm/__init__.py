"""Operators for preparing training corpora. Nothing else in metricspark imports this subpackage."""
