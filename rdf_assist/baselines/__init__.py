"""The systems that the methods are compared with."""
