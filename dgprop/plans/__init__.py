"""How plans are run and checked: lineage, adaptive scope, exchanges, hot keys."""
