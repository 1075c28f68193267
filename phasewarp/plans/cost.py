"""Cost figures of a run, from counts that are already at hand."""

from __future__ import annotations


def explain_cost(tokens: int, distinct: int, phases: int, kept: int, edges: int, rounds: int = 30, n: int = 30, m: int = 30, methods: int = 10, band: int | None = None) -> dict[str, float]:
    """What each stage reads or makes: tokens scanned, keys shuffled, pairs, rank steps, cells."""
    width = m if band is None else min(m, 2 * band + 1)
    return {
        "tokens_scanned": tokens,
        "keys_shuffled": min(tokens, distinct * phases),
        "pairs_after_cutoff": kept * (kept - 1) / 2,
        "pairs_without_cutoff": distinct * (distinct - 1) / 2,
        "rank_steps": edges * rounds * phases,
        "cells": n * width * methods,
    }
