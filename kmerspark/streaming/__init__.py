"""Online counting, normalization of streams, and windows over events."""
