"""Operators that Spark lacks, as compositions of its own."""
