"""Core operators: identity, canonicalisation, hierarchy, baselines, metrics, data tests, profiling, report."""
