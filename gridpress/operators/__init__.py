"""Operators on grids: transform, plane coder, factor coder, codec, resampling, spectra, and relational surroundings."""
