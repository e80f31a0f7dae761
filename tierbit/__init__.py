"""A tiered-bitmap search and verification engine on Spark."""
