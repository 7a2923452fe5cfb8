"""Graph-fingerprint analytics over labelled collections, as Spark DataFrame plans."""
