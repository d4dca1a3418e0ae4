"""Where facts, triples and rules come from and go to."""
