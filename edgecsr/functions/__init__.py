"""functions of the edge-list and CSR engine."""
