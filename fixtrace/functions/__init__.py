"""Column functions and per-row kernels: text similarity, syntax trees, version order, storage helpers."""
