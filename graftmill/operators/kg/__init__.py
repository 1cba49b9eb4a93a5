"""Knowledge graphs: triples (h, r, t) of strings."""
