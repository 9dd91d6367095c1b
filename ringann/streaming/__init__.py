"""Query streams, insert streams and event profiles."""
