"""Set synchronisation for Spark: digests, sliced filters, XOR cells, baselines and byte ledgers."""
