"""From joined rows to pairs: the inverted index, its chunks, and scoring."""
