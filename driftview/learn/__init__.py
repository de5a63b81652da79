"""Losses, incremental and closed-form training, method choice, and classes beyond two."""
