"""Readers, sinks, stages and lifts of the given tables to geometries."""
