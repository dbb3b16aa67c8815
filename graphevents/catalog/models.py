"""Trained models and the experiment workloads; filled in by ``graphevents.workloads``."""

from __future__ import annotations

from .. import workloads

QUERIES: dict = {name: (f, None) for name, f in workloads.QUERIES.items()}
