"""How plans are materialised between steps."""
