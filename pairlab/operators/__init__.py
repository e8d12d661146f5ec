"""Operators on pairs, rollouts and rewards; each takes and returns DataFrames."""
