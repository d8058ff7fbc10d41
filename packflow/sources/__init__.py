"""Tables, keyed corpora and synthetic partitions."""
