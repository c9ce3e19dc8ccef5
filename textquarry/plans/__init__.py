"""Query plans by area; importing `load` registers them all."""

from __future__ import annotations

import importlib

AREAS = ("q_curation", "q_dedup", "q_web", "q_ops", "q_lm", "q_flow", "q_translate", "q_layout", "q_speech", "q_align", "q_stream")


def load() -> None:
    for area in AREAS:
        importlib.import_module(f".{area}", __name__)
