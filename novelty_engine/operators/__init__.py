"""The methods: networks, axes, duels, overall and temporal scores, evolution graphs, baselines and measures."""
