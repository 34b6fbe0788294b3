"""Tables in, pairs out."""
