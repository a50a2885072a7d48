"""Structured Streaming: updates from cleaned batches, rules and windows over events, running location models."""
