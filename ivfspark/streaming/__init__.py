"""Structured Streaming: continuous index updates, windows over the update stream, stateful latest rows."""
