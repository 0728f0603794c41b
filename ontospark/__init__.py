"""Ontological query answering on Spark: rules are compiled into unions of conjunctive queries."""
