"""Methods that the moment tree is compared with."""
