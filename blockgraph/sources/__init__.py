"""Readers and writers: the graph suite, edge text, block stores."""
