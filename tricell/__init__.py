"""Triangle enumeration and cyclic joins for very large edge tables on Spark."""
