"""Training, capture, replay, spectral update, baselines, measures and provenance algebra."""
