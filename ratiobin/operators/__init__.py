"""Codec phases, measures, baselines and the relational operators around them."""
