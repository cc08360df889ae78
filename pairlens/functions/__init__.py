"""pairlens functions."""
