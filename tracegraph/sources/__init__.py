"""Inputs: graphs over the given tables, file and stream readers, sinks, the trace generator."""
