"""Inputs and outputs: triples, tables, dataset pairs, sinks."""
