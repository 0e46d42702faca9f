"""Models that grow with a stream: only summaries are kept."""
