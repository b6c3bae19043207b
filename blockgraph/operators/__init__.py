"""Graph preparation, exchanges along stripes, and joins that Spark lacks."""
