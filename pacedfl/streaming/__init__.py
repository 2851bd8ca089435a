"""Structured Streaming forms of link telemetry, uploads and residual state."""
