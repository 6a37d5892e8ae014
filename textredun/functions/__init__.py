"""Column functions over spectra, and the SQL surface."""
