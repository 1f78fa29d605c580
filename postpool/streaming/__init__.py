"""The incremental index as a Structured Streaming job."""
