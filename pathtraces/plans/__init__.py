"""How plans are cut and sized: shared storage, checked broadcasts."""
