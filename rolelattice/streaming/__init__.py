"""Query logs and policy changes as streams."""
