"""Samples of streams: bounded reservoirs by window, and summaries folded batch by batch."""
