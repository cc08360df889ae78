"""pairlens streaming."""
