"""Streams of samples: windows, scoring and mini-batch updates."""
