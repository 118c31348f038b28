"""Reading and writing tables, coordinate files and grid stores."""
