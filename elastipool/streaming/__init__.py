"""The live service on Structured Streaming."""
