"""Elements out of texts, and the measures as SQL functions."""
