"""Set algebra and SQL functions."""
