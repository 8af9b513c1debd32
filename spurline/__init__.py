"""Branch-aware density clustering and its neighbours, as DataFrame plans."""
