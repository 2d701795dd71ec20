"""Methods on coordinate-format DataFrames: basis, structure constants, expansion, assembly, propagation, spectra."""
