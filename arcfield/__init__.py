"""arcfield: spherical spatial search expressed as Spark plans."""
