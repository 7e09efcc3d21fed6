"""Group-capped centre selection on Spark: small, balanced summaries of very large point sets."""
