"""Reading, writing and generating points."""
