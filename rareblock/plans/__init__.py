"""How plans are cut, stored and resumed."""
