"""How the operators are put together and which physical form each takes."""
