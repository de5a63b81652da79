"""Bands, policies, the clustered store and the view itself."""
