"""Windows, shortcuts, kernels, release and relational helpers."""
