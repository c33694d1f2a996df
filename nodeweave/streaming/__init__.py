"""Structured Streaming: binned signals, scoring, online EM, spells and joins over time."""
