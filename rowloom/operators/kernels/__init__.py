"""In-memory kernels on small integer code matrices (one block of rows each); no Spark here."""
