"""Operators over graphs: preparation, enumeration, decomposition counts, fragments, mining, profiling, baselines."""
