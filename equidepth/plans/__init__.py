"""Key codes, samples, models, slices and sorts."""
