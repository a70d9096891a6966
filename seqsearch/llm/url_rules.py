"""Hand-written URL patterns, a line each: verdict | literal tokens that every URL that fits has | regular expression.

The expressions are read alike by Java, RE2 and Python and see the URL with A-Z in lower case.  Groups repeat a bounded number
of times, since Java's matcher calls itself for each.
"""

from __future__ import annotations

LINES = r"""
block | ads | [/._-]ads[/._-]
block | adserver | [/._-]adserver[/._-]
block | adclick | [/._?&-]adclick[/._=-]
block | doubleclick | ://([^/?#]*[.])?doubleclick[.]
block | banner | [/._-]banner[/._-]
block | banners | [/._-]banners[/._-]
block | popup | [/._-]popup[/._-]
block | popunder | [/._-]popunder[/._-]
block | sponsored | /sponsored([/._-]|$)
block | advertorial | /advertorial([/._-]|$)
block | tracker | [/._-]tracker[/._-]
block | pixel gif | /pixel[.]gif
block | beacon | /beacon([/?._-]|$)
block | casino | [/._-]casino[/._-]
block | poker | ://([^/?#]*[.-])?poker[.-]
block | slots | ://([^/?#]*[.-])?slots[.-]
block | betting | ://([^/?#]*[.-])?betting[.-]
block | free | [/._-]free[._-]bets[/._0-9-]
block | payday loans | [/._-]payday[._-]loans([/._-]|$)
block | cheap pills | [/._-]cheap[._-]pills([/._-]|$)
block | viagra | [/._-]viagra([/._-]|$)
block | cialis | [/._-]cialis([/._-]|$)
block | replica watches | [/._-]replica[._-]watches([/._-]|$)
block | porn | [/._-]porn[/._-]
block | porno | [/._-]porno[/._-]
block | xxx | [/._-]xxx[/._-]
block | sex tube | [/._-]sex[._-]tube[/._-]
block | cams | ://([^/?#]*[.-])?cams[.-]
block | escorts | ://([^/?#]*[.-])?escorts[.-]
block | warez | [/._-]warez[/._-]
block | torrent | [/._-]torrent([/._-]|$)
block | torrents | [/._-]torrents([/._-]|$)
block | keygen | [/._-]keygen([/._-]|$)
block | serial crack | [/._-]serial[._-]crack([/._-]|$)
block | crack download | [/._-]crack[._-]download([/._-]|$)
block | spam | ://([^/?#]*[.-])?spam-farm[0-9]*[.-]
block | spam mill | ://([^/?#]*[.-])?spam-mill[.-]
block | link farm | ://([^/?#]*[.-])?link-farm[.-]
block | click farm | ://([^/?#]*[.-])?click-farm[.-]
block | click bait | ://([^/?#]*[.-])?click-bait[.-]
block | content farm | ://([^/?#]*[.-])?content-farm[.-]
block | content mill | ://([^/?#]*[.-])?content-mill[.-]
block | link exchange | [/._-]link-exchange[/._-]
block | guestbook | /guestbook([/.?_-]|$)
block | doorway | /doorway([/._-]|$)
block | parked domain | [/._-]parked-domain[/._-]
block | domain for sale | [/._-]domain-for-sale([/._-]|$)
block | wp login php | /wp-login[.]php
block | wp admin | /wp-admin(/|$)
block | xmlrpc php | /xmlrpc[.]php
block | cgi bin | /cgi-bin/
block | phpmyadmin | /phpmyadmin(/|$)
block | administrator index php | /administrator/index[.]php
block | signin | /signin([/?]|$)
block | login | /login([/?.]|$)
block | logout | /logout([/?.]|$)
block | register | /register([/?.]|$)
block | checkout | /checkout([/?]|$)
block | cart | /cart([/?]|$)
block | redirect http | [?&]redirect=http(:|%3a)
block | redirect https | [?&]redirect=https(:|%3a)
block | url http | [?&]url=http(:|%3a)
block | replytocom | [?&]replytocom=[0-9]+
block | print | [?&]print=(1|yes|true)
block | sid | [?&]sid=[0-9a-f]{16,}
block | phpsessid | [?&]phpsessid=[0-9a-z]{16,}
block | jsessionid | ;jsessionid=[0-9a-z]{16,}
block | utm source | [?&]utm_source=
block | utm campaign | [?&]utm_campaign=
block | gclid | [?&]gclid=
block | fbclid | [?&]fbclid=
block | calendar day | /calendar/([^?#]*/)?day/
block | tag | /tag/[^/?#]+/page/[0-9]+
block | feed | /feed/?([?#]|$)
block | rss xml | /rss[.]xml([?#]|$)
block | exe | [.]exe([?#]|$)
block | apk | [.]apk([?#]|$)
block | zip | [.]zip([?#]|$)
block | | ://[0-9]{1,3}([.][0-9]{1,3}){3}[:/]
block | | ://([^/?#-]*-){5}
block | | [?&](session|sess|token)=[0-9a-f]{16,}
block | | ://[^/?#]+(/[^/?#]+){15}
"""
