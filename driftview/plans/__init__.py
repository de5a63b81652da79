"""Whole runs as DataFrame programs."""
