"""Scans, segmenters, parsers and sinks."""
