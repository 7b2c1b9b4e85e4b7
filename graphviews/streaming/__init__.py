"""Views over streams: native windowed operators and the network in micro-batches."""
