"""Structured Streaming: live assignment, windows, mini-batch updates."""
