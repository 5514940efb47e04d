"""Append-only streams of events and triples; an extension, the methods themselves work on static graphs."""
