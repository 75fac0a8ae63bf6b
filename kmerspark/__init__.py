"""k-mer sketch analytics on Spark: counting, spectra, trimming and normalization over short sequences."""
