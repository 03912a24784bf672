"""Provenance of conjunctive queries over tables seen through rule mappings and an inclusion ontology."""
