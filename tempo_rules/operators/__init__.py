"""Matching, scoring, mining, pruning, detection, evaluation, completion."""
