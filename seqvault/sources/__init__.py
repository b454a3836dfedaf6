"""Readers and views over the given tables and over FASTA files."""
