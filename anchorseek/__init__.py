"""Locality-aware sequence membership search, written for Spark DataFrames."""
