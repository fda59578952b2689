"""Iterative ranking plans, baselines, experiments and their SQL twins."""
