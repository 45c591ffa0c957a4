"""Planning on the gate list: locality, cache blocking, costs and placement. Never touches amplitudes."""
