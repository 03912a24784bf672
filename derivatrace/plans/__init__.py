"""Query, ontology and mapping representations, rewriting and unfolding: driver-side plans without data."""
