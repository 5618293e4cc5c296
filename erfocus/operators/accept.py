"""Acceptance of proposals."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def greedy(delta: float) -> bool:
    """Only strict improvements."""
    return delta > 0


def mh(delta: float, log_forward: float, log_reverse: float, temperature: float, u: float) -> bool:
    """Metropolis-Hastings: the ratio of densities times that of the reverse to the forward proposal.

    A move whose reverse cannot be proposed is rejected.  At temperature 0 it is the sign of delta.
    """
    if log_reverse == -math.inf:
        return False
    if temperature <= 0:
        return delta > 0
    log_ratio = delta / temperature + log_reverse - log_forward
    return log_ratio >= 0 or math.log(max(u, 1e-300)) < log_ratio


def mh_column(delta: Column, log_forward: Column, log_reverse: Column, temperature: float, u: Column) -> Column:
    return u < F.least(F.lit(1.0), F.exp(delta / temperature + log_reverse - log_forward))
