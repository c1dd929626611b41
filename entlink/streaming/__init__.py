"""Structured Streaming: alerts on arriving mentions, model pointers."""
