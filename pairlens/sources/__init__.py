"""pairlens sources."""
