"""Single-task kernels in plain Python: no Spark import here."""
