"""Time windows, streams and incremental trees."""
