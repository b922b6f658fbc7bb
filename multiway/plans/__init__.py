"""Cost formulas and the choices that follow from them."""
