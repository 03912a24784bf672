"""Structured Streaming: derived facts and answers over append-only rows."""
