"""The methods: quantizers, encoding, matching, search, query sets, graphs, baselines and measures."""
