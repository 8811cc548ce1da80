"""Event streams and incremental Gram matrices."""
