"""Operators on graphs: balls, spectra, filters, gates, engines and the index."""
