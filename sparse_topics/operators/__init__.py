"""The methods: matrix preparation, half steps, truncation, factorisation loops, measures, baselines."""
