"""Views kept up to date by streams."""
