"""Driver-side plans: linked schemas, networks, slot graphs, families."""
