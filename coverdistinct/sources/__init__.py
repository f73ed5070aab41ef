"""Element streams from tables and files, and sinks for sketch state."""
