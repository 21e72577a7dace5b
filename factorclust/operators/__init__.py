"""The methods: normalisation, the factor solver, rounding, baselines, measures."""
