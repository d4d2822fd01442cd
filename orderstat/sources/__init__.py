"""Tables, rank lists, scratch files, formats."""
