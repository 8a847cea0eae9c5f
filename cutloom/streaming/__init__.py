"""Streams of events as graphs: windows, co-activity edges, running degrees."""
