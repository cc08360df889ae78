"""pairlens: audit of summarisation corpora and systems on Spark DataFrames."""
