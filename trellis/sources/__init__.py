"""Where triples come from and how they are placed."""
