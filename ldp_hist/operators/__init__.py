"""Frequency oracles, heavy-hitter protocols, baselines and measures."""
