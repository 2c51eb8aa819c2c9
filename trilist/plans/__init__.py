"""trilist.plans"""
