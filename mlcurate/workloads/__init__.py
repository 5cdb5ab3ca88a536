"""Experiment workloads and operator demonstrations, each with its SQL twin where SQL can express it."""

from mlcurate.workloads import dedup, evaluation, filters, lid, operators, pipelines, precision, rehydration, reports, unspaced  # noqa: F401
from mlcurate.workloads.registry import ORACLES, QUERIES  # noqa: F401

from mlcurate.workloads.rehydration import flagship  # noqa: F401
