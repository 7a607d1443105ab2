"""Area kernels: interchangeable ways to the same exact intersection and union areas of polygon pairs."""
