"""Experiment workloads and operator entries over the given tables, each with the SQL that it is held against."""
