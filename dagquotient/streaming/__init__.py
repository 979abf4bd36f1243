"""Event streams: windowed counts and label traces that are kept up to date."""
