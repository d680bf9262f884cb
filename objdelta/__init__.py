"""objdelta: a Spark-native delta store for the successive states of evolving object graphs."""
