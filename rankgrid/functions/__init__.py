"""Serial kernels on tiles and column expressions; no Spark job starts here."""
