"""pairlens operators."""
