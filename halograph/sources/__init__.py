"""Tables and the particle systems built from them."""
