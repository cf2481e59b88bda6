"""Streams of new tuples: degrees, heavy keys and joins kept up to date."""
