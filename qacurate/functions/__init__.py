"""Column expressions: tokens, sets, hashes, vectors. All stay in the JVM."""
