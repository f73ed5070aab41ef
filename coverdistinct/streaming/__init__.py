"""The estimators on Structured Streaming."""
