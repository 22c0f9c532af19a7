"""Part of the engine for search and clustering by noisy comparisons."""
