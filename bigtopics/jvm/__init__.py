"""The block sampler for Spark's own processes: Java source compiled once a session by the compiler that Spark brings."""
