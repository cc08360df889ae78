"""pairlens plans."""
