"""Ontology-mediated navigational queries over property graphs, on Spark."""
