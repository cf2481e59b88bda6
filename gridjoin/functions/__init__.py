"""Exact planning mathematics: linear programs, hypergraphs, measures."""
