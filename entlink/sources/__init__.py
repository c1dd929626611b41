"""Entity tuples, mentions, triples and XML entries."""
