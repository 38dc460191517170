"""Rating streams: windowed counts, deduplication, and folding new ratings into a model."""
