"""Query engine that mixes joins, degree partitioning and matrix products."""
