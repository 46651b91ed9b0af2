"""Where edges come from: files, streams, generators and the given tables."""
